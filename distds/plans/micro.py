"""One operation at a time: the comparisons between variants of a structure's operations, as plans over one input each."""

from __future__ import annotations

import inspect
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from distds.operators.bloom import BlockedBloom, ScatterBloom
from distds.operators.keyed_table import KeyedTable, StagedWriter
from distds.operators.queues import PhaseQueue, RingQueue
from distds.plans import contigs, kmers, sorting
from distds.plans.engines import ENGINES
from distds.plans.promises import Promise
from distds.sources.io import settle, table


def program_lengths() -> dict[str, int]:
    """Non-blank source lines of each sort, count and contig program (helpers that several share are not counted)."""
    programs = [f for m in (sorting, kmers, contigs) for name, f in vars(m).items() if name.startswith(("sort_", "count_", "contigs_")) and name != "sort_keys"]
    return {f.__name__: sum(bool(line.strip()) for line in inspect.getsource(f).splitlines()) for f in programs}


def insert_direct(rows: DataFrame, messages: int = 16) -> DataFrame:
    """Unbuffered: every message is an insert of its own against the table that the one before left."""
    t = KeyedTable.create(rows.sparkSession, "long", "long")
    for i in range(messages):
        t, _ = t.insert(rows.filter(F.pmod(F.xxhash64("key"), F.lit(messages)) == i), on_dup="merge", merge=F.sum)
        t = KeyedTable(settle(t.state))
    return t.items()


def insert_buffered(rows: DataFrame, messages: int = 16) -> DataFrame:
    """The same messages staged and flushed together."""
    w = StagedWriter(KeyedTable.create(rows.sparkSession, "long", "long"), on_dup="merge", merge=F.sum)
    for i in range(messages):
        w.insert(rows.filter(F.pmod(F.xxhash64("key"), F.lit(messages)) == i))
    return w.flush().items()


def operations(spark: SparkSession, d: str) -> dict[str, callable]:
    """Name -> plan. Hosts: one hot queue, or one for each of eight ranks."""
    li = table(spark, d, "lineitem").select(F.lit(0).cast("long").alias("seq"), F.col("l_orderkey").alias("key"), F.col("l_quantity").cast("long").alias("val"))
    li, o = settle(li), table(spark, d, "orders").select(F.col("o_orderkey").alias("key"), F.col("o_totalprice").alias("val"))
    asks = li.withColumn("seq", F.xxhash64("key") % 1_000_000_007)
    t = KeyedTable(settle(o))
    op = F.when(F.col("event_type").isin("signup", "error"), "pop").otherwise("push")
    log = settle(table(spark, d, "events").select(F.col("event_id").alias("seq"), (F.col("user_id") % 8).alias("rank"), op.alias("op"), F.col("event_id").alias("item"), F.col("user_id").alias("x")))
    one, many = log.withColumn("host", F.lit(0).cast("long")), log.withColumn("host", F.col("rank"))
    out = {"table_insert_direct": lambda: insert_direct(li), "table_insert_buffered": lambda: insert_buffered(li), "table_find_atomic": lambda: t.find(asks.select("seq", "key"), Promise.FIND | Promise.INSERT), "table_find_only": lambda: t.find(asks.select("seq", "key"), Promise.FIND)}
    for name, rows in (("one", one), ("many", many)):
        push = rows.filter("op = 'push'")
        out |= {
            f"ring_atomic_{name}": lambda r=rows: RingQueue.create(spark, 1000).run_log(r, rows=20_000).select("seq", "ok", "pos"),
            f"ring_relaxed_{name}": lambda r=push: RingQueue.create(spark, 1 << 40).run_log(r, Promise.PUSH).select("seq", "ok", "pos"),
            f"phase_push_{name}": lambda r=push: PhaseQueue.create(spark, 1 << 40).push(r)[1],
        }
    keys = log.select("seq", F.concat_ws("#", "x", F.col("seq") % 50).alias("x"))
    out |= {"filter_scattered": lambda: ScatterBloom(1 << 20).insert(keys), "filter_blocked": lambda: BlockedBloom(1 << 14).insert(keys)}
    out |= {f"engine_{e}": lambda f=f: f(many.select("host", "seq")) for e, f in ENGINES.items()}
    return out


#: Pairs whose ratio is of interest: slower first.
RATIOS = {"direct/buffered insert": ("table_insert_direct", "table_insert_buffered"), "atomic/only find": ("table_find_atomic", "table_find_only"), "atomic/relaxed push, many": ("ring_atomic_many", "ring_relaxed_many"), "atomic/relaxed push, one": ("ring_atomic_one", "ring_relaxed_one"), "relaxed ring/phase push, many": ("ring_relaxed_many", "phase_push_many"), "scattered/blocked filter": ("filter_scattered", "filter_blocked")}


def seconds(make, repeats: int = 2) -> float:
    """The least time of a plan over a few runs; its rows go nowhere."""
    best = float("inf")
    for _ in range(repeats):
        t = time.time()
        make().write.format("noop").mode("overwrite").save()
        best = min(best, time.time() - t)
    return best
