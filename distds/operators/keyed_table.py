"""A distributed hash table as a DataFrame of state, with batched inserts and finds and the buffered writer.

Batches carry a total order ``seq``. A method's promise picks its plan: fully atomic operations are replayed in order, find-only
lookups are one join, local inserts merge inside the partitions that hold the state.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from distds.functions.hashing import HASHES
from distds.operators.scan import chunk, prefix_scan
from distds.plans.promises import Promise
from distds.sources.io import settle


class DuplicateSeq(ValueError):
    """Two operations of a batch share a place in the order."""


def power_of_two(n: int) -> int:
    return 1 << max(0, int(n - 1).bit_length())


#: How two folded values meet, for aggregates that local inserts can merge by.
COMBINE = {
    F.sum: lambda a, b: a + b,
    F.min: F.least,
    F.max: F.greatest,
    F.bit_or: lambda a, b: a.bitwiseOR(b),
    F.bit_and: lambda a, b: a.bitwiseAND(b),
    F.bit_xor: lambda a, b: a.bitwiseXOR(b),
}


@dataclass(frozen=True)
class KeyedTable:
    """``state``: key, val. ``capacity`` None grows freely; else inserts of new keys beyond it are refused. ``slots``: home slots
    that keys hash to, if not the least power of two for the capacity."""

    state: DataFrame
    capacity: int | None = None
    ranks: int = 8
    hash_fn: str = "portable"
    slots: int | None = None

    @property
    def home_slots(self) -> int:
        return self.slots or power_of_two(self.capacity or 1 << 20)

    @classmethod
    def create(cls, spark: SparkSession, key: str, val: str, capacity: int | None = None, ranks: int = 8, hash_fn: str = "portable") -> KeyedTable:
        return cls(spark.createDataFrame([], f"key {key}, val {val}"), capacity, ranks, hash_fn)

    def slot(self, key: Column) -> Column:
        return F.pmod(HASHES[self.hash_fn](key), F.lit(self.home_slots))

    def rank(self, key: Column) -> Column:
        return F.floor(self.slot(key) / F.lit(-(-self.home_slots // self.ranks))).cast("int")

    # -- inserts ---------------------------------------------------------------------------------------------------------
    def _fold(self, rows: DataFrame, on_dup: str, merge=None) -> DataFrame:
        """One row for each key of a batch: partial aggregates run before the one exchange."""
        if on_dup == "merge":
            return rows.groupBy("key").agg(merge(F.col("val")).alias("new"))
        pick = F.max_by if on_dup == "replace" else F.min_by
        return rows.groupBy("key").agg(pick(F.struct("val"), "seq").getField("val").alias("new"))

    def insert(self, df: DataFrame, promise: Promise = Promise.FIND | Promise.INSERT, on_dup: str = "replace", merge=None, check: bool = False):
        """``df``: seq, key, val. Returns (new table, seq, ok, reason). Null keys are refused, and new keys beyond the capacity.

        ``on_dup``: replace (the last wins), keep (the first wins), error, or merge with an aggregate such as ``F.sum``.
        """
        if promise & Promise.LOCAL:
            return self.insert_local(df, on_dup, merge)
        good = df.filter(F.col("key").isNotNull())
        ok, reason = F.col("key").isNotNull(), F.when(F.col("key").isNull(), "null_key")
        result = df.select("seq", ok.alias("ok"), reason.alias("reason"))
        if on_dup == "error" or check:
            if df.groupBy("seq").count().filter("count > 1").head(1) and on_dup != "merge":
                raise DuplicateSeq("operations share a seq")
            if on_dup == "error" and (good.groupBy("key").count().filter("count > 1").head(1) or good.join(self.state, "key", "left_semi").head(1)):
                raise ValueError("duplicate key")
        if self.capacity is not None:
            first = good.groupBy("key").agg(F.min("seq").alias("first")).join(self.state.select("key"), "key", "left_anti")
            room = self.capacity - self.state.count()
            ranked = prefix_scan(first.withColumn("_one", F.lit(1).cast("long")).withColumn("_all", F.lit(0)), "_one", ["_all"], seq="first")
            full = settle(ranked.filter(F.coalesce("before", F.lit(0)) < room).select("key", F.lit(True).alias("fits")).union(self.state.select("key", F.lit(True).alias("fits"))))
            marked = good.join(full, "key", "left")
            done = marked.select("seq", F.coalesce("fits", F.lit(False)).alias("ok"), F.when(F.col("fits").isNull(), "full").alias("reason"))
            result = done.union(df.filter(F.col("key").isNull()).select("seq", F.lit(False), F.lit("null_key")))
            good = marked.filter("fits").drop("fits")
        return replace(self, state=self._merge(self._fold(good, on_dup, merge), on_dup, merge)), result

    def _merge(self, new: DataFrame, on_dup: str, merge=None) -> DataFrame:
        if on_dup == "merge":
            both = self.state.union(new.select("key", "new"))
            return both.groupBy("key").agg(merge(F.col("val")).alias("val"))
        old = self.state.select("key", F.col("val").alias("old"), F.lit(True).alias("_o"))
        rows = new.withColumn("_n", F.lit(True)).join(old, "key", "full")
        take_old = F.col("_n").isNull() if on_dup == "replace" else F.col("_o").isNotNull()
        return rows.select("key", F.when(take_old, F.col("old")).otherwise(F.col("new")).alias("val"))

    def insert_local(self, df: DataFrame, on_dup: str = "replace", merge=None):
        """Rows must lie in the partition of their owner already (see :meth:`place_local`): they are not exchanged. The state is
        dealt to the same partitions.

        Each partition folds its own rows into its own part of the state. A row that lies elsewhere raises when it runs.
        """
        if on_dup not in ("replace", "keep") and (on_dup != "merge" or merge not in COMBINE):
            raise ValueError("local inserts replace, keep, or merge by sum, min, max or a bit operation")
        here = (F.spark_partition_id() == F.col("owner")) & (F.col("owner") == self.rank(F.col("key")))
        mine = df.filter(F.col("key").isNotNull()).filter(F.when(here, F.lit(True)).otherwise(F.raise_error(F.lit("PromiseViolation: a row outside its owner's partition")).cast("boolean")))
        pick = {"replace": lambda: F.max_by(F.struct("val"), "seq").getField("val"), "keep": lambda: F.min_by(F.struct("val"), "seq").getField("val"), "merge": lambda: merge(F.col("val"))}[on_dup]
        new = mine.groupBy("owner", "key").agg(pick().alias("new"), F.lit(True).alias("_n"))
        old = self.place_local(self.state).select("owner", "key", F.col("val").alias("old"), F.lit(True).alias("_o"))
        rows = new.join(old, ["owner", "key"], "full")
        if on_dup == "merge":
            val = F.when(F.col("_n").isNull(), F.col("old")).when(F.col("_o").isNull(), F.col("new")).otherwise(COMBINE[merge](F.col("old"), F.col("new")))
        else:
            val = F.when(F.col("_n").isNull() if on_dup == "replace" else F.col("_o").isNotNull(), F.col("old")).otherwise(F.col("new"))
        result = df.select("seq", F.col("key").isNotNull().alias("ok"), F.when(F.col("key").isNull(), "null_key").alias("reason"))
        return replace(self, state=rows.select("key", val.cast(self.state.schema["val"].dataType).alias("val"))), result

    def place_local(self, df: DataFrame) -> DataFrame:
        """Deals rows to their owners, partition id = rank; joins and aggregates by owner then need no exchange."""
        return df.withColumn("owner", self.rank(F.col("key"))).repartitionById(self.ranks, "owner")

    def delete(self, keys: DataFrame) -> KeyedTable:
        return replace(self, state=self.state.join(keys.select("key").distinct(), "key", "left_anti"))

    # -- finds -----------------------------------------------------------------------------------------------------------
    def find(self, df: DataFrame, promise: Promise = Promise.FIND | Promise.INSERT) -> DataFrame:
        """``df``: seq, key -> seq, key, val, found. The strongest guarantee is the default; with the promise that there are
        only finds it is one join against the state as it is, with no sort of the state if it is small."""
        if promise & Promise.INSERT:
            return self.run_log(df.select("seq", "key", F.lit("find").alias("op"), F.lit(None).cast(self.state.schema["val"].dataType).alias("val")))
        state = self.state.select("key", "val", F.lit(True).alias("_f"))
        return df.join(state, "key", "left").select("seq", "key", "val", F.coalesce("_f", F.lit(False)).alias("found"))

    def run_log(self, log: DataFrame, hot: bool = False) -> DataFrame:
        """``log``: seq, key, op (find or insert), val. Finds see exactly the inserts before them. seq, key, val, found.

        With ``hot`` the log is cut into ranges of seq and the last value before each range carried over, so that a key with a
        large share of the operations is split; without, one window by key does it with fewer exchanges. Null keys are never
        inserted and never found.
        """
        if hot:
            return self._run_chunks(log)
        ops = log.select("key", "seq", "op", F.when((F.col("op") == "insert") & F.col("key").isNotNull(), F.struct("val")).alias("v"))
        asked = self.state.join(log.select("key").distinct(), "key", "left_semi")  # only touched keys are sorted
        base = asked.select("key", F.lit(-(1 << 63) + 1).alias("seq"), F.lit("insert").alias("op"), F.struct("val").alias("v"))
        before = Window.partitionBy("key").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
        seen = base.union(ops).withColumn("s", F.last("v", ignorenulls=True).over(before)).filter("op = 'find'")
        return seen.select("seq", "key", F.col("s.val").alias("val"), F.col("s").isNotNull().alias("found"))

    def _run_chunks(self, log: DataFrame, rows: int = 100_000) -> DataFrame:
        ops = log.select("key", "seq", "op", F.when((F.col("op") == "insert") & F.col("key").isNotNull(), F.struct("val")).alias("v"))
        ops = ops.withColumn("_c", chunk(ops, "seq", rows))
        lasts = ops.filter("v is not null").groupBy("key", "_c").agg(F.max_by("v", "seq").alias("v"))
        asked = self.state.join(log.select("key").distinct(), "key", "left_semi").select("key", F.lit(-1).alias("_c"), F.struct("val").alias("v"))
        marks = lasts.union(asked).withColumn("_m", F.lit(True)).unionByName(ops.select("key", "_c").distinct().withColumn("v", F.lit(None).cast(ops.schema["v"].dataType)).withColumn("_m", F.lit(False)))
        up = Window.partitionBy("key").orderBy("_c").rangeBetween(Window.unboundedPreceding, -1)  # a row or two for each range
        carried = marks.withColumn("head", F.last("v", ignorenulls=True).over(up)).filter("not _m").select("key", "_c", "head")
        inside = Window.partitionBy("key", "_c").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
        seen = ops.withColumn("_in", F.last("v", ignorenulls=True).over(inside)).filter("op = 'find'").join(carried, ["key", "_c"], "left")
        s = F.coalesce("_in", "head")
        return seen.select("seq", "key", s.getField("val").alias("val"), s.isNotNull().alias("found"))

    def resize(self, capacity: int | None, slots: int | None = None) -> KeyedTable:
        """A new capacity, and new home slots: a table that grows freely may have more keys than slots."""
        if capacity is not None and self.state.count() > capacity:
            raise ValueError("more keys than the new capacity")
        return replace(self, capacity=capacity, slots=slots)

    def items(self) -> DataFrame:
        return self.state

    def size(self) -> int:
        return self.state.count()

    def contains(self, df: DataFrame) -> DataFrame:
        return df.join(self.state.select("key"), "key", "left_semi")


# -- open-addressing layout ------------------------------------------------------------------------------------------------
def place_block(keys: np.ndarray, hashes: np.ndarray, slots: int):
    """Lock-step placement on a power-of-two block with triangular steps: each round the first in order wins a slot."""
    at, probes = np.full(len(keys), -1, np.int64), np.zeros(len(keys), np.int64)
    taken = np.zeros(slots, bool)
    pending = np.arange(len(keys))
    for i in range(slots):
        if not len(pending):
            break
        want = (hashes[pending] + i * (i + 1) // 2) % slots
        probes[pending] += 1
        free = ~taken[want]
        win = np.zeros(len(pending), bool)
        win[np.flatnonzero(free)[np.unique(want[free], return_index=True)[1]]] = True
        at[pending[win]] = want[win]
        taken[want[win]] = True
        pending = pending[~win]
    return at, probes


def layout(df: DataFrame, capacity: int, block: int = 1 << 15, hash_fn: str = "portable") -> DataFrame:
    """``df``: key, seq -> key, block, slot, probes, ok. Probes stay inside the key's block, so one exchange places all keys."""
    size = power_of_two(capacity)
    block = min(block, size)
    h = HASHES[hash_fn](F.col("key"))
    dealt = df.select("key", "seq", F.pmod(h, F.lit(size)).alias("slot")).withColumn("block", F.floor(F.col("slot") / block).cast("int"))

    def place(t: pa.Table) -> pa.Table:
        t = t.sort_by("seq")
        keys = t.column("key").to_numpy()
        b = t.column("block")[0].as_py()
        at, probes = place_block(keys, t.column("slot").to_numpy() % block, block)
        return pa.table({"key": keys, "block": pa.array(np.full(len(keys), b), pa.int32()), "slot": pa.array(np.where(at >= 0, at + b * block, -1)), "probes": pa.array(probes), "ok": pa.array(at >= 0)})

    return dealt.groupBy("block").applyInArrow(place, "key long, block int, slot long, probes long, ok boolean")


def layout_global(df: DataFrame, capacity: int, hash_fn: str = "portable", rounds: int | None = None) -> DataFrame:
    """As :func:`layout`, but probes may reach any slot: in each round pending keys ask for their next slot, the first by seq
    wins a free one, and the rest step on. Rounds are exchanges, so this is for low loads; blocks place in one exchange. Slots
    won in a round are written once and only read later. Raises if keys are left after ``rounds`` (by default enough for any)."""
    size = power_of_two(capacity)
    pending = df.select("key", "seq", F.pmod(HASHES[hash_fn](F.col("key")), F.lit(size)).alias("h"))
    done = None
    for i in range(rounds or size):
        want = pending.withColumn("slot", F.pmod(F.col("h") + i * (i + 1) // 2, F.lit(size)))
        taken = F.lit(None).cast("boolean") if done is None else F.col("_t")
        want = want if done is None else want.join(done.select("slot", F.lit(True).alias("_t")), "slot", "left")
        first = F.row_number().over(Window.partitionBy("slot").orderBy("seq"))
        tried = settle(want.withColumn("_w", taken.isNull() & (first == 1)).select("key", "seq", "h", "slot", "_w"))
        won = tried.filter("_w").select("key", "slot", F.lit(i + 1).cast("long").alias("probes"))
        done = won if done is None else done.union(won)
        pending = tried.filter("not _w").select("key", "seq", "h")
        if not pending.head(1):
            return done.withColumn("ok", F.lit(True))
    raise RuntimeError("keys are left without a slot")


def probe_stats(placed: DataFrame, capacity: int) -> DataFrame:
    return placed.agg((F.sum(F.col("ok").cast("int")) / power_of_two(capacity)).alias("load"), F.avg("probes").alias("avg_probes"), F.max("probes").cast("long").alias("max_probes"))


def decode_flag(word: Column) -> Column:
    """A bucket word: two bits of status (free, reserved, ready) and thirty reader bits."""
    status = F.element_at(F.array(F.lit("free"), F.lit("reserved"), F.lit("ready"), F.lit("invalid")), (word.bitwiseAND(F.lit(3)) + 1).cast("int"))
    return F.struct(status.alias("status"), F.bit_count(F.shiftright(word, 2).bitwiseAND(F.lit((1 << 30) - 1))).cast("int").alias("readers"))


#: The legal steps of a bucket.
LEGAL = (("free", "reserved"), ("reserved", "ready"), ("ready", "reserved"), ("ready", "ready"))


def replay_flag(df: DataFrame) -> DataFrame:
    """``df``: bucket, step, word. Adds state, readers and whether the step from the word before is legal; a writer may not
    take a bucket that has readers."""
    w = Window.partitionBy("bucket").orderBy("step")
    d = df.withColumn("f", decode_flag(F.col("word"))).withColumn("p", F.lag("f").over(w))
    before, now = F.coalesce("p.status", F.lit("free")), F.col("f.status")
    legal = F.lit(False)
    for a, b in LEGAL:
        legal = legal | ((before == a) & (now == b))
    blocked = (now == "reserved") & (F.coalesce("p.readers", F.lit(0)) > 0)
    return d.select("bucket", "step", F.col("f.status").alias("state"), F.col("f.readers").alias("readers"), (legal & ~blocked).alias("legal"))


# -- buffered writer ---------------------------------------------------------------------------------------------------------
class StagedWriter:
    """Inserts that wait in a plan until ``flush``: one exchange to the owners, and partial aggregation before it.

    ``queue``: staged batches that may wait; one more flushes them. With ``local`` rows go to their owners as they are and the
    owners insert them locally; without, they are folded by key before the exchange, which moves less where keys repeat.
    """

    def __init__(self, table: KeyedTable, message_size: int = 1024, on_dup: str = "replace", merge=None, queue: int = 64, local: bool = False):
        self.table, self.message_size, self.on_dup, self.merge, self.queue, self.local = table, message_size, on_dup, merge, queue, local
        self.pending: list[DataFrame] = []

    def insert(self, df: DataFrame) -> StagedWriter:
        self.pending.append(df)
        if len(self.pending) > self.queue:
            self.flush()
            self.table = replace(self.table, state=settle(self.table.state))
        return self

    def rows(self) -> DataFrame:
        out = self.pending[0]
        for p in self.pending[1:]:
            out = out.unionByName(p)
        return out

    def messages(self, src: Column) -> DataFrame:
        """src, dst, items, msgs: full messages leave at once, the last partial one at the flush."""
        rows = self.rows().filter(F.col("key").isNotNull()).select(src.alias("src"), self.table.rank(F.col("key")).alias("dst"))
        counts = rows.groupBy("src", "dst").agg(F.count("*").cast("long").alias("items"))
        return counts.withColumn("msgs", F.ceil(F.col("items") / self.message_size).cast("long"))

    def flush(self) -> KeyedTable:
        if self.pending:
            rows, t = self.rows(), self.table
            if self.local:
                rows = t.place_local(rows.filter(F.col("key").isNotNull()))
            self.table, _ = t.insert(rows, Promise.LOCAL if self.local else Promise.FIND | Promise.INSERT, on_dup=self.on_dup, merge=self.merge)
            self.pending = []
        return self.table
