"""Mixing sources to target weights by weighted sampling without replacement.

Every document gets the key ``-ln(u) / weight`` (weight: its quality); the smallest keys come first. A source whose target
exceeds its size is taken in complete epochs first, and the rest of its budget is filled from the front of the key order.

Edge cases: a null text has size 0; a null source is a source of its own and sorts last; a source without words has target 0;
null or non-positive quality counts as 1; repeated rows are drawn one by one (ties by doc_id, size); an empty table gives an
empty mix; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from distds.llm.scratch import Scratch, only, word_count

#: Key buckets by source: only the one bucket in which the budget ends is ever sorted.
KEY_BUCKETS = 4096


def ranked_sources(scratch: Scratch, sources: DataFrame) -> DataFrame:
    """Adds ``pos``: the place of each source by code point, null last; ranges are ranked apart and then offset."""
    runs = scratch.stash(sources.repartitionByRange(F.col("source").asc_nulls_last()).withColumn("run", F.spark_partition_id()))
    before = Window.orderBy("run").rowsBetween(Window.unboundedPreceding, -1)  # one row for each range
    offsets = runs.groupBy("run").count().select("run", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("off"))
    place = F.row_number().over(Window.partitionBy("run").orderBy(F.col("source").asc_nulls_last()))
    return runs.withColumn("place", place).join(offsets, "run").withColumn("pos", F.col("off") + F.col("place") - 1).drop("run", "off", "place")


def level(table: DataFrame, total: float) -> float:
    """The multiple of its weight that each source gets when targets stop at ``cap`` and the excess is shared again."""
    lam = -1.0
    while True:
        full = (F.col("cap") <= F.lit(lam) * F.col("weight")) if lam >= 0 else F.lit(False)
        r = table.agg(F.sum(F.when(full, F.col("cap"))).alias("c"), F.sum(F.when(~full, F.col("weight"))).alias("w")).first()
        if not r["w"]:
            return lam if lam >= 0 else 0.0
        new = (total - (r["c"] or 0.0)) / r["w"]
        if new <= lam:
            return lam
        lam = new


def mix(docs: DataFrame, *, source_weights=(5, 2, 1), share: float = 1.5, max_epochs: float = 2.0, quality: DataFrame | None = None, keep: tuple = ()) -> DataFrame:
    """One row for each document: doc_id, source, size, source_size, target, taken (words, repeats counted), and ``keep``.

    ``quality``: doc_id and q, one row for each doc_id; the key order follows q. Each source's taken words differ from its target by half
    of one document at most.
    """
    scratch = Scratch(docs.sparkSession)
    docs = only(docs, "doc_id", "source", "text", *keep)
    size = word_count(F.col("text"))
    u = (F.conv(F.substring(F.md5(F.concat_ws("#", F.coalesce(F.col("doc_id").cast("string"), F.lit("")), size.cast("string"))), 1, 13), 16, 10).cast("double") + 0.5) / float(1 << 52)
    base = docs.select("doc_id", "source", size.alias("size"), (-F.log(u)).alias("e"), *keep)
    base = base.withColumn("q", F.lit(1.0)) if quality is None else base.join(quality.select("doc_id", "q"), "doc_id", "left")
    base = base.withColumn("key", F.col("e") / F.when(F.col("q") > 0, F.col("q").cast("double")).otherwise(1.0)).drop("e", "q")
    base = base.withColumn("b", F.least(F.lit(KEY_BUCKETS - 1), F.floor((1 - F.exp(-F.col("key"))) * KEY_BUCKETS)).cast("int"))
    base = scratch.stash(base.withColumn("src", F.coalesce(F.concat(F.lit("s"), "source"), F.lit("n"))))

    sums = scratch.stash(base.groupBy("src", "source", "b").agg(F.sum("size").alias("s")))
    sources = ranked_sources(scratch, sums.groupBy("src", "source").agg(F.sum("s").alias("source_size")))
    weights = F.array(*[F.lit(float(x)) for x in source_weights])
    sources = sources.withColumn("weight", F.element_at(weights, (F.col("pos") % len(source_weights) + 1).cast("int")))
    sources = scratch.stash(sources.withColumn("cap", F.col("source_size") * F.lit(float(max_epochs))))
    total = float(sources.agg(F.sum("source_size")).first()[0] or 0)
    lam = level(sources, share * total)
    sources = sources.withColumn("target", F.least("cap", F.lit(lam) * F.col("weight")))
    sources = sources.withColumn("epochs", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long"))
    sources = sources.withColumn("rest", F.col("target") - F.col("epochs") * F.col("source_size"))

    upto = Window.partitionBy("src").orderBy("b")  # at most KEY_BUCKETS rows
    cum = sums.withColumn("after", F.sum("s").over(upto)).withColumn("before", F.col("after") - F.col("s"))
    ends = cum.join(sources.select("src", "rest"), "src").filter((F.col("before") <= F.col("rest")) & (F.col("after") > F.col("rest")))
    sources = scratch.stash(sources.join(ends.select("src", F.col("b").alias("end_b"), F.col("before").alias("end_before")), "src", "left"))

    rows = base.join(sources.select("src", "source_size", "target", "epochs", "rest", "end_b", "end_before"), "src")
    clear = rows.filter(F.coalesce(F.col("b") != F.col("end_b"), F.lit(True))).withColumn("chosen", F.coalesce(F.col("b") < F.col("end_b"), F.lit(False)))
    order = Window.partitionBy("src").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    edge = rows.filter(F.col("b") == F.col("end_b")).withColumn("in_b", F.coalesce(F.sum("size").over(order), F.lit(0)))
    edge = edge.withColumn("chosen", F.col("end_before") + F.col("in_b") + F.col("size") / 2 <= F.col("rest")).drop("in_b")
    both = clear.unionByName(edge)
    taken = F.col("size") * (F.col("epochs") + F.col("chosen").cast("long"))
    copies = F.col("epochs") + F.col("chosen").cast("long")
    return both.select("doc_id", "source", "size", "source_size", "target", taken.cast("long").alias("taken"), copies.cast("int").alias("copies"), *keep)
