"""Atomics as op-logs: each operation returns what it would have read, had the log run in the order of ``seq``."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from distds.operators.scan import chunk_replay, combine, one, prefix_scan


def _fetch(df: DataFrame, value: str, op: str, init: int) -> DataFrame:
    out = prefix_scan(df, value, ["addr"], op)
    before = combine(op, F.lit(init).cast("long"), F.col("before"))
    return out.withColumn("before", before.cast("long"))


def fetch_add(df: DataFrame, init: int = 0) -> DataFrame:
    """addr, seq, delta -> before."""
    return _fetch(df, "delta", "sum", init)


def fetch_or(df: DataFrame, init: int = 0) -> DataFrame:
    return _fetch(df, "mask", "bit_or", init)


def fetch_and(df: DataFrame, init: int = -1) -> DataFrame:
    return _fetch(df, "mask", "bit_and", init)


def fetch_xor(df: DataFrame, init: int = 0) -> DataFrame:
    return _fetch(df, "mask", "bit_xor", init)


def _rows(t: pa.Table):
    return sorted(zip(t.column("seq").to_pylist(), t.column("expect").to_pylist(), t.column("new").to_pylist()))


def _summarise(t: pa.Table) -> pa.Table:
    """A run of swaps as a finite map: first values that end as another value; all others pass unchanged."""
    at: dict[int, set] = {}
    moved: set = set()
    for _, e, n in _rows(t):
        src = at.pop(e, set())
        if e not in moved:
            src = src | {e}
            moved.add(e)
        if src:
            at[n] = at.get(n, set()) | src | (set() if n in moved else {n})
            moved.add(n)
    pairs = [(s, v) for v, ss in at.items() for s in ss]
    return pa.table({"addr": [one(t, "addr")], "_c": pa.array([one(t, "_c")], pa.int32()), "src": pa.array([[p[0] for p in pairs]], pa.list_(pa.int64())), "dst": pa.array([[p[1] for p in pairs]], pa.list_(pa.int64()))})


def cas_log(df: DataFrame, init: int = 0, rows: int = 100_000) -> DataFrame:
    """addr, seq, expect, new -> old, swapped. Swaps of a chunk compose to a finite map, so a hot address is split."""

    def starts(t: pa.Table) -> pa.Table:
        value, out = init, []
        for c, src, dst in sorted(zip(t.column("_c").to_pylist(), t.column("src").to_pylist(), t.column("dst").to_pylist())):
            out.append((c, value))
            value = dict(zip(src, dst)).get(value, value)
        return pa.table({"addr": pa.array([one(t, "addr")] * len(out), pa.int64()), "_c": pa.array([c for c, _ in out], pa.int32()), "start": pa.array([v for _, v in out], pa.int64())})

    def replay(t: pa.Table, s: pa.Table) -> pa.Table:
        value, addr, out = one(s, "start"), one(t, "addr"), []
        for q, e, n in _rows(t):
            out.append((q, value, value == e))
            value = n if value == e else value
        return pa.table({"addr": pa.array([addr] * len(out), pa.int64()), "seq": pa.array([o[0] for o in out], pa.int64()), "old": pa.array([o[1] for o in out], pa.int64()), "swapped": pa.array([o[2] for o in out], pa.bool_())})

    df = df.select(F.col("addr").cast("long"), F.col("seq").cast("long"), F.col("expect").cast("long"), F.col("new").cast("long"))
    return chunk_replay(df, "addr", _summarise, starts, replay, "addr long, _c int, src array<long>, dst array<long>", "addr long, _c int, start long", "addr long, seq long, old long, swapped boolean", rows=rows)


def cas_retry(df: DataFrame) -> DataFrame:
    """addr, round, seq -> attempts: any atomic built on compare-and-swap. In each try the lowest pending seq of an address wins."""
    return df.withColumn("attempts", F.row_number().over(Window.partitionBy("addr", "round").orderBy("seq")))
