"""Prefix scans over op-logs in two passes: chunks of the order are folded apart, then offset.

A chunk is a range of ``seq`` with about ``rows`` operations, so one hot address or host never becomes one task; only chunk
summaries meet in a window. Ranges follow quantiles of ``seq``, so gaps and outliers in it do not fill one chunk.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

ROWS = 100_000
#: Quantile cuts of an order: found by comparisons, and more of them between two of those; beyond that it is cut evenly.
CUTS, MORE = 256, 16
FOLDS = {"sum": F.sum, "max": F.max, "min": F.min, "bit_or": F.bit_or, "bit_and": F.bit_and, "bit_xor": F.bit_xor}


def place(x: Column, cuts: list[int]) -> Column:
    """How many of the sorted ``cuts`` are at most ``x``: a tree of comparisons."""

    def tree(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(x < F.lit(cuts[mid]), tree(lo, mid)).otherwise(tree(mid + 1, hi))

    return tree(0, len(cuts))


def chunk(df: DataFrame, seq: str = "seq", rows: int = ROWS) -> Column:
    """The chunk of each operation, from one small aggregate over the log."""
    n, low, high = df.agg(F.count(seq), F.min(seq), F.max(seq)).first()
    want = -(-n // rows)
    if want < 2:
        return F.lit(0)
    points = min(want, CUTS * MORE)
    got = df.agg(F.percentile_approx(seq, [i / points for i in range(1, points)], max(10_000, 8 * points))).first()[0]
    cuts = sorted(set(got) - {low})
    if points <= CUTS:
        return place(F.col(seq), cuts).cast("int")
    top, edges = cuts[MORE - 1 :: MORE], [low, *cuts, high + 1]
    at, x = place(F.col(seq), top), F.col(seq)
    groups = F.array(*[F.array(*[F.lit(c) for c in cuts[i * MORE : (i + 1) * MORE - 1]]).cast("array<bigint>") for i in range(len(top) + 1)])
    at = at * MORE + F.aggregate(F.element_at(groups, at + 1), F.lit(0), lambda n, c: n + (c <= x).cast("int"))
    fine = -(-want // len(edges))  # parts between two cuts
    if fine < 2:
        return at.cast("int")
    lo = F.element_at(F.array(*[F.lit(e) for e in edges]), at + 1)
    width = F.element_at(F.array(*[F.lit(max(1, -(-(b - a) // fine))) for a, b in zip(edges, edges[1:])]), at + 1)
    return (at * fine + F.floor((x - lo) / width)).cast("int")


def combine(op: str, a: Column, b: Column) -> Column:
    both = {"sum": a + b, "max": F.greatest(a, b), "min": F.least(a, b), "bit_or": a.bitwiseOR(b), "bit_and": a.bitwiseAND(b), "bit_xor": a.bitwiseXOR(b)}[op]
    return F.when(a.isNull(), b).when(b.isNull(), a).otherwise(both)


def prefix_scan(df: DataFrame, value: str, by: list[str], op: str = "sum", seq: str = "seq", out: str = "before", rows: int = ROWS, ties: tuple[str, ...] = ()) -> DataFrame:
    """Adds ``out``: the fold of ``value`` over the earlier operations of the same ``by``; null for the first. ``ties`` order
    operations of one ``seq``."""
    fold = FOLDS[op]
    df = df.withColumn("_c", chunk(df, seq, rows))
    up = Window.partitionBy(*by).orderBy("_c").rowsBetween(Window.unboundedPreceding, -1)  # a row for each chunk
    heads = df.groupBy(*by, "_c").agg(fold(value).alias("_t")).select(*by, "_c", fold("_t").over(up).alias("_head"))
    inside = Window.partitionBy(*by, "_c").orderBy(seq, *ties).rowsBetween(Window.unboundedPreceding, -1)
    rows_ = df.withColumn("_in", fold(value).over(inside))
    return rows_.join(heads, [*by, "_c"]).withColumn(out, combine(op, F.col("_head"), F.col("_in"))).drop("_c", "_in", "_head")


def chunk_replay(df: DataFrame, by: str, summarise, starts, replay, summary_schema: str, start_schema: str, schema: str, seq: str = "seq", rows: int = ROWS, init: DataFrame | None = None) -> DataFrame:
    """Replays operations whose effect on a small state composes over chunks.

    ``summarise(ops) -> table`` folds a chunk to its function; ``starts(summaries) -> table`` gives each chunk its first state;
    ``replay(ops, start) -> table`` runs the chunk from there. All get arrow tables sorted by nothing in particular. ``init``
    adds columns to the summaries by ``by``: the state before the log.
    """
    df = df.withColumn("_c", chunk(df, seq, rows))
    folded = df.groupBy(by, "_c").applyInArrow(summarise, summary_schema)
    folded = folded if init is None else folded.join(init, by, "left")
    first = folded.groupBy(by).applyInArrow(starts, start_schema)
    return df.groupBy(by, "_c").cogroup(first.groupBy(by, "_c")).applyInArrow(replay, schema)


def one(table: pa.Table, name: str):
    return table.column(name)[0].as_py()
