"""Connected components of an edge table by alternating star contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from distds.llm.scratch import Scratch


def components(scratch: Scratch, edges: DataFrame, rounds: int = 60) -> DataFrame:
    """``edges``: a, b (long). Returns node, root: the smallest node of its component, for all nodes with edges.

    Each round points every node at the smallest neighbour it knows, first from larger nodes and then from smaller ones.
    Only minima are kept for a node, so a node with many edges is aggregated before it moves; the number of rounds grows
    with the logarithm of the longest path. Links stay in tables of the shared folder.
    """
    e = scratch.stash(edges.filter("a != b").select(F.greatest("a", "b").alias("v"), F.least("a", "b").alias("u")).distinct())
    for _ in range(rounds):
        both = e.select("v", "u").union(e.select(F.col("u").alias("v"), F.col("v").alias("u")))
        low = scratch.stash(both.groupBy("v").agg(F.least(F.min("u"), F.col("v")).alias("m")))  # written, so that joins can split a hot node
        large = both.filter("u > v").join(low, "v").select(F.col("u").alias("v"), F.col("m").alias("u"))
        large = scratch.stash(large.filter("v != u").distinct())
        down = scratch.stash(large.groupBy("v").agg(F.min("u").alias("m")))
        small = large.join(down, "v").filter("u != m").select(F.col("u").alias("v"), F.col("m").alias("u"))
        old, new = e, scratch.stash(small.union(down.select("v", F.col("m").alias("u"))).distinct())
        ends = new.select(F.col("v").alias("x"), F.lit(1).alias("child"), F.lit(0).alias("head")).union(new.select("u", F.lit(0), F.lit(1)).distinct())
        scratch.drop(old, low, large, down)
        mixed = ends.groupBy("x").agg(F.sum("child").alias("c"), F.max("head").alias("h")).filter("c > 1 or (c = 1 and h = 1)")
        if not mixed.head(1):  # every node hangs on one root, and no root on another node
            return new.select(F.col("v").alias("node"), F.col("u").alias("root")).union(new.select(F.col("u").alias("node"), F.col("u").alias("root")).distinct())
        e = new
    raise RuntimeError("components did not settle")
