"""Hosted queues as op-logs: the phase queue (one kind of operation between barriers) and the ring (both kinds at once).

Many queues are one DataFrame keyed by ``host``. Single-kind phases are prefix scans. Mixed logs replay the occupancy rule
``x -> min(cap, max(0, x +- 1))``; such functions compose to ``min(hi, max(lo, x + d))``, so a hot host is cut into chunks that
are folded apart. Vectors are accepted as a whole or refused; a chunk of those moves each range of first occupancies by one
amount, and these few ranges are its summary.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from distds.operators.scan import chunk_replay, one, prefix_scan
from distds.plans.promises import Promise, PromiseViolation

DONE = "host long, seq long, op string, n long, ok boolean"


def clamp_walk(steps: np.ndarray, x: int, cap: int):
    """(occupancy before each step, occupancy at the end) of a walk that stays within 0 and ``cap``.

    From a point on the walk follows the free sum, pushed up at 0, until it would pass ``cap``, or pushed down at ``cap``, until
    it would fall below 0; the one that holds longer is taken, a whole stretch at a time.
    """
    out, at, size = np.empty(len(steps), np.int64), 0, 64
    while at < len(steps):
        free = x + np.cumsum(steps[at : at + size])
        up = free - np.minimum(np.minimum.accumulate(free), 0)
        down = free - np.maximum(np.maximum.accumulate(free) - cap, 0)
        over, under = up > cap, down < 0
        a, b = (int(np.argmax(bad)) if bad.any() else len(free) for bad in (over, under))
        walk, n = (up, a) if a >= b else (down, b)
        out[at] = x
        out[at + 1 : at + n] = walk[: n - 1]
        x, at = int(walk[n - 1]), at + n
        size = min(2 * size, 1 << 16) if n == len(free) else max(64, 2 * n)
    return out, x


def offsets(done: DataFrame, value: str, bounds: DataFrame | None, rows: int) -> DataFrame:
    """host, seq, op, ok, pos: items that successful operations of a kind took before, counted from the queue's bounds."""
    counted = prefix_scan(done, value, ["host", "op"], rows=rows)
    pos = F.coalesce("before", F.lit(0))
    if bounds is not None:
        counted = counted.join(bounds.select("host", "head", "tail"), "host", "left")
        pos = pos + F.coalesce(F.when(F.col("op") == "push", F.col("tail")).otherwise(F.col("head")), F.lit(0))
    return counted.select("host", "seq", "op", "ok", F.when(F.col("ok"), pos).alias("pos"))


def _held(bounds: DataFrame | None) -> DataFrame | None:
    return None if bounds is None else bounds.select("host", (F.col("tail") - F.col("head")).alias("x0"))


def _first(t: pa.Table) -> int:
    return (one(t, "x0") or 0) if "x0" in t.column_names else 0


def _starts(t: pa.Table, x: int, end) -> pa.Table:
    """The occupancy before each chunk of a host, in order; ``end(row, x)`` is the one after it."""
    t, out = t.sort_by("_c"), []
    for row in range(len(t)):
        out.append(x)
        x = end(t, row, x)
    return pa.table({"host": t.column("host"), "_c": t.column("_c"), "start": pa.array(out, pa.int64())})


def clamp_log(log: DataFrame, capacity: int, rows: int = 100_000, bounds: DataFrame | None = None) -> DataFrame:
    """host, seq, op (push or pop) -> host, seq, op, ok, pos: positions count successful pushes and pops of a host, on from
    ``bounds`` (host, head, tail)."""

    def steps(t: pa.Table) -> np.ndarray:
        return np.where(t.column("op").to_numpy(zero_copy_only=False) == "push", 1, -1)

    def summarise(t: pa.Table) -> pa.Table:
        s = steps(t.sort_by("seq"))
        return pa.table({"host": pa.array([one(t, "host")], pa.int64()), "_c": pa.array([one(t, "_c")], pa.int32()), "d": [int(s.sum())], "lo": [clamp_walk(s, 0, capacity)[1]], "hi": [clamp_walk(s, capacity, capacity)[1]]})

    def starts(t: pa.Table) -> pa.Table:
        d, lo, hi = (t.sort_by("_c").column(c).to_pylist() for c in ("d", "lo", "hi"))
        return _starts(t, _first(t), lambda _, i, x: min(hi[i], max(lo[i], x + d[i])))

    def replay(t: pa.Table, s: pa.Table) -> pa.Table:
        t = t.sort_by("seq")
        step = steps(t)
        before, _ = clamp_walk(step, one(s, "start"), capacity)
        ok = np.where(step > 0, before < capacity, before > 0)
        return pa.table([t.column("host"), t.column("seq"), t.column("op"), pa.array(np.ones(len(t), np.int64)), pa.array(ok)], names=["host", "seq", "op", "n", "ok"])

    slim = log.select(F.col("host").cast("long").alias("host"), F.col("seq").cast("long").alias("seq"), "op")
    done = chunk_replay(slim, "host", summarise, starts, replay, "host long, _c int, d long, lo long, hi long", "host long, _c int, start long", DONE, rows=rows, init=_held(bounds))
    return offsets(done.withColumn("_n", F.col("ok").cast("long")), "_n", bounds, rows)


def vector_ranges(ops: list[str], sizes: list[int], cap: int):
    """(firsts, shifts): a queue that starts with x items, x in the range from one first to the next, ends with x + shift."""
    first, last, shift = np.zeros(1, np.int64), np.full(1, cap, np.int64), np.zeros(1, np.int64)
    for op, n in zip(ops, sizes):
        bar = (cap - n if op == "push" else n - 1) - shift  # the last first occupancy below or at the bar
        cut = np.flatnonzero((first <= bar) & (bar < last))
        if len(cut):
            first, shift = np.concatenate([first, bar[cut] + 1]), np.concatenate([shift, shift[cut]])
            last = np.concatenate([last, last[cut]])
            last[cut] = bar[cut]
        x = first + shift
        fits = x + n <= cap if op == "push" else x >= n
        shift = shift + np.where(fits, n if op == "push" else -n, 0)
    order = np.argsort(first)
    return first[order], shift[order]


def vector_log(log: DataFrame, capacity: int, rows: int = 100_000, bounds: DataFrame | None = None) -> DataFrame:
    """host, seq, op, n -> host, seq, op, ok, pos: vectors that do not fit, or of which fewer are there, fail as a whole."""

    def ordered(t: pa.Table):
        t = t.sort_by("seq")
        return t, t.column("op").to_pylist(), t.column("n").to_pylist()

    def summarise(t: pa.Table) -> pa.Table:
        first, shift = vector_ranges(*ordered(t)[1:], capacity)
        lists = [pa.array([x.tolist()], pa.list_(pa.int64())) for x in (first, shift)]
        return pa.table({"host": pa.array([one(t, "host")], pa.int64()), "_c": pa.array([one(t, "_c")], pa.int32()), "first": lists[0], "shift": lists[1]})

    def starts(t: pa.Table) -> pa.Table:
        def end(t, row, x):
            first, shift = (t.column(c)[row].as_py() for c in ("first", "shift"))
            return x + shift[int(np.searchsorted(first, x, "right")) - 1]

        return _starts(t, _first(t), end)

    def replay(t: pa.Table, s: pa.Table) -> pa.Table:
        (t, ops, sizes), x, ok = ordered(t), one(s, "start"), []
        for op, n in zip(ops, sizes):
            good = x + n <= capacity if op == "push" else x >= n
            x += (n if op == "push" else -n) * good
            ok.append(good)
        return pa.table([t.column("host"), t.column("seq"), t.column("op"), t.column("n"), pa.array(ok, pa.bool_())], names=["host", "seq", "op", "n", "ok"])

    slim = log.select(F.col("host").cast("long").alias("host"), F.col("seq").cast("long").alias("seq"), "op", F.col("n").cast("long").alias("n"))
    done = chunk_replay(slim, "host", summarise, starts, replay, "host long, _c int, first array<long>, shift array<long>", "host long, _c int, start long", DONE, rows=rows, init=_held(bounds))
    return offsets(done.withColumn("_n", F.when(F.col("ok"), F.col("n")).otherwise(0)), "_n", bounds, rows)


@dataclass(frozen=True)
class PhaseQueue:
    """``items``: host, pos, item between head and tail; ``bounds``: host, head, tail. One kind of operation in a phase."""

    items: DataFrame
    bounds: DataFrame
    capacity: int

    @classmethod
    def create(cls, spark, capacity: int, item: str = "long"):
        return cls(spark.createDataFrame([], f"host long, pos long, item {item}"), spark.createDataFrame([], "host long, head long, tail long"), capacity)

    def _placed(self, df: DataFrame) -> DataFrame:
        df = df.withColumn("host", F.col("host").cast("long")).withColumn("_one", F.lit(1).cast("long"))
        return prefix_scan(df, "_one", ["host"]).withColumn("k", F.coalesce("before", F.lit(0))).drop("before", "_one").join(self.bounds, "host", "left").withColumn("head", F.coalesce("head", F.lit(0))).withColumn("tail", F.coalesce("tail", F.lit(0)))

    def push(self, df: DataFrame):
        """host, seq, item -> (queue, result host, seq, ok, pos, slot). One fetch-add each: positions are a prefix scan."""
        rows = self._placed(df).withColumn("pos", F.col("tail") + F.col("k")).withColumn("ok", F.col("pos") - F.col("head") < self.capacity)
        res = rows.select("host", "seq", "ok", F.when(F.col("ok"), F.col("pos")).alias("pos"), F.when(F.col("ok"), F.col("pos") % self.capacity).alias("slot"))
        return self._append(rows), res

    def pop(self, df: DataFrame):
        """host, seq -> (queue, result host, seq, ok, pos, item): the k-th pop of a phase gets the k-th item."""
        rows = self._placed(df).withColumn("pos", F.col("head") + F.col("k")).withColumn("ok", F.col("pos") < F.col("tail"))
        res = rows.filter("ok").select("host", "seq", "ok", "pos").join(self.items, ["host", "pos"]).select("host", "seq", "ok", "pos", "item")
        failed = rows.filter("not ok").select("host", "seq", "ok", F.lit(None).cast("long").alias("pos"), F.lit(None).cast(self.items.schema["item"].dataType).alias("item"))
        took = rows.filter("ok").groupBy("host").agg(F.max("pos").alias("m"))
        bounds = self.bounds.join(took, "host", "left").select("host", F.coalesce(F.col("m") + 1, "head").alias("head"), "tail")
        left = self.items.join(bounds, "host").filter(F.col("pos") >= F.col("head")).select("host", "pos", "item")
        return replace(self, items=left, bounds=bounds), res.union(failed)

    @staticmethod
    def place_local(df: DataFrame, hosts: int) -> DataFrame:
        """Deals rows of hosts 0 to ``hosts`` - 1 to the partition of their host: partition id = host."""
        return df.withColumn("host", F.col("host").cast("int")).repartitionById(hosts, "host")

    def local_push(self, df: DataFrame, hosts: int):
        """host, seq, item in the partition of its host (see :meth:`place_local`) -> (queue, result host, seq, ok, pos).

        Each host appends its own rows, which are not exchanged. A row that lies elsewhere raises when it runs.
        """
        here = F.when(F.spark_partition_id() == F.col("host"), F.lit(True)).otherwise(F.raise_error(F.lit("PromiseViolation: a local push from another host")).cast("boolean"))
        w = Window.partitionBy("host").orderBy("seq")
        rows = df.filter(here).withColumn("k", F.row_number().over(w) - 1)
        rows = rows.join(self.place_local(self.bounds, hosts), "host", "left").withColumn("host", F.col("host").cast("long"))
        head, tail = F.coalesce("head", F.lit(0)), F.coalesce("tail", F.lit(0))
        rows = rows.withColumn("pos", (tail + F.col("k")).cast("long")).withColumn("ok", F.col("pos") - head < self.capacity)
        return self._append(rows.withColumn("head", head)), rows.select("host", "seq", "ok", F.when(F.col("ok"), F.col("pos")).alias("pos"))

    def _append(self, rows: DataFrame):
        got = rows.filter("ok")
        ends = got.groupBy("host").agg(F.max("pos").alias("m"), F.min("head").alias("h"))
        bounds = self.bounds.join(ends, "host", "full").select("host", F.coalesce("head", "h").alias("head"), F.coalesce(F.col("m") + 1, "tail").alias("tail"))
        return replace(self, items=self.items.union(got.select("host", "pos", "item")), bounds=bounds)

    def local_pop(self, host: int, n: int) -> DataFrame:
        """The first n items of a host, read where they lie: a filter, no exchange."""
        head = self.bounds.filter(F.col("host") == host).select("head").first()
        a = head["head"] if head else 0
        return self.items.filter((F.col("host") == host) & F.col("pos").between(a, a + n - 1))

    def refreshes(self, result: DataFrame) -> DataFrame:
        """host, refreshes: pushes that met the cached bound and had to read the remote head."""
        return result.groupBy("host").agg(F.sum((~F.col("ok")).cast("long")).alias("refreshes"))

    def resize(self, capacity: int):
        worst = self.bounds.agg(F.max(F.col("tail") - F.col("head"))).first()[0] or 0
        if worst > capacity:
            raise ValueError("a queue holds more items than the new capacity")
        return replace(self, capacity=capacity)

    def slots(self) -> DataFrame:
        return self.items.select("host", "pos", (F.col("pos") % self.capacity).alias("slot"), "item")

    def migrate(self, where: DataFrame):
        """``where``: host, new_host. Items and bounds move; other hosts stay."""

        def move(d: DataFrame) -> DataFrame:
            names = d.columns
            return d.join(where, "host", "left").withColumn("host", F.coalesce("new_host", "host")).select(*names)

        return replace(self, items=move(self.items), bounds=move(self.bounds))

    def drain(self) -> DataFrame:
        """host, items in order: one array for each host; for queues that fit a task."""
        got = self.items.groupBy("host").agg(F.array_sort(F.collect_list(F.struct("pos", "item"))).alias("a"))
        return got.select("host", F.transform("a", lambda x: x["item"]).alias("items"))

    @staticmethod
    def check_phases(log: DataFrame) -> None:
        if log.groupBy("phase").agg(F.count_distinct("op").alias("k")).filter("k > 1").head(1):
            raise PromiseViolation("a phase holds pushes and pops")


class RingQueue(PhaseQueue):
    """The queue that also takes mixed logs; single-kind promises fall back to the cheaper scans."""

    def run_log(self, log: DataFrame, promise: Promise = Promise.PUSH | Promise.POP, rows: int = 100_000) -> DataFrame:
        """host, seq, op, item -> host, seq, op, ok, pos, item on top of what the queue holds: the k-th successful pop returns
        the k-th item. Operations that the promise rules out are refused."""
        return self.apply(log, promise, rows)[1]

    def apply(self, log: DataFrame, promise: Promise = Promise.PUSH | Promise.POP, rows: int = 100_000):
        """(queue after the log, result as of :meth:`run_log`)."""
        log = log.withColumn("host", F.col("host").cast("long"))
        if promise == Promise.PUSH | Promise.POP:
            done = clamp_log(log, self.capacity, rows, self.bounds)
        else:
            done = self._single(log, promise.name.lower(), rows)
        pushed = done.filter("ok and op = 'push'").join(log.select("host", "seq", "item"), ["host", "seq"]).select("host", "pos", "item")
        every = self.items.unionByName(pushed)
        result = done.join(every, ["host", "pos"], "left").select("host", "seq", "op", "ok", "pos", "item")
        return self._after(every, done.withColumn("n", F.lit(1))), result

    def apply_vectors(self, log: DataFrame, rows: int = 100_000):
        """host, seq, op, n, items (array, for pushes) -> (queue, result host, seq, op, ok, pos, items): whole vectors or none."""
        log = log.withColumn("host", F.col("host").cast("long")).withColumn("n", F.col("n").cast("long"))
        done = vector_log(log, self.capacity, rows, self.bounds).join(log.select("host", "seq", "n", "items"), ["host", "seq"])
        pushed = done.filter("ok and op = 'push'").select("host", F.col("pos").alias("p0"), F.posexplode("items").alias("i", "item"))
        every = self.items.unionByName(pushed.select("host", (F.col("p0") + F.col("i")).alias("pos"), "item"))
        asked = done.filter("ok and op = 'pop' and n > 0").select("host", "seq", F.explode(F.sequence("pos", F.col("pos") + F.col("n") - 1)).alias("pos"))
        got = asked.join(every, ["host", "pos"]).groupBy("host", "seq").agg(F.array_sort(F.collect_list(F.struct("pos", "item"))).alias("a"))  # one vector
        got = got.select("host", "seq", F.transform("a", lambda x: x["item"]).alias("popped"))
        result = done.join(got, ["host", "seq"], "left").select("host", "seq", "op", "ok", "pos", F.when(F.col("op") == "push", F.col("items")).otherwise(F.col("popped")).alias("items"))
        return self._after(every, done), result

    def _after(self, every: DataFrame, done: DataFrame):
        def moved(op: str):
            return F.sum(F.when(F.col("ok") & (F.col("op") == op), F.col("n")).otherwise(0)).cast("long")

        moves = done.groupBy("host").agg(moved("pop").alias("h"), moved("push").alias("t"))
        add = [(F.coalesce(a, F.lit(0)) + F.coalesce(b, F.lit(0))).cast("long").alias(a) for a, b in (("head", "h"), ("tail", "t"))]
        bounds = self.bounds.join(moves, "host", "full").select("host", *add)
        left = every.join(bounds.select("host", "head"), "host").filter(F.col("pos") >= F.col("head")).select("host", "pos", "item")
        return replace(self, items=left, bounds=bounds)

    def _single(self, log: DataFrame, op: str, rows: int) -> DataFrame:
        mine = F.col("op") == op
        scan = prefix_scan(log.withColumn("_one", mine.cast("long")), "_one", ["host"], rows=rows).join(self.bounds, "host", "left")
        head, tail = F.coalesce("head", F.lit(0)), F.coalesce("tail", F.lit(0))
        pos = F.coalesce("before", F.lit(0)) + (tail if op == "push" else head)
        ok = mine & ((pos - head < self.capacity) if op == "push" else (pos < tail))
        return scan.select("host", "seq", "op", ok.alias("ok"), F.when(ok, pos).cast("long").alias("pos"))


def ready(df: DataFrame) -> DataFrame:
    """host, pos, done_at -> visible_at when completion is published by compare-and-swap: all earlier ones must have finished."""
    out = prefix_scan(df.select("host", "pos", "done_at"), "done_at", ["host"], "max", seq="pos")
    return out.select("host", "pos", "done_at", F.greatest("done_at", F.coalesce("before", "done_at")).alias("visible_at"))


def ready_fault(df: DataFrame) -> DataFrame:
    """The same log published by fetch-add: the k-th completion makes position k readable, whether written or not.

    host, pos, shown_at, done_at of positions that are readable before they are written.
    """
    kth = prefix_scan(df.select("host", F.col("pos").alias("at"), F.lit(1).cast("long").alias("_one"), F.col("done_at").alias("shown_at")), "_one", ["host"], seq="shown_at", ties=("at",))
    shown = kth.select("host", F.coalesce("before", F.lit(0)).alias("pos"), "shown_at")
    return shown.join(df.select("host", "pos", "done_at"), ["host", "pos"]).filter("shown_at < done_at")
