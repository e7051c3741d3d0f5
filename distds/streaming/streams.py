"""Streams over the event log: windowed sums, a queue and a filter as keyed state, buffered writes and dedup.

Sources are directories of Parquet slices; every stream writes Parquet through a sink in the shared folder, so nothing gathers in
the driver. ``run`` processes what is there and stops; the same definitions run continuously with another trigger.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StatefulProcessor

from distds.operators.bloom import BlockedBloom
from distds.sources.io import shared_path

ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
PROVIDER = "spark.sql.streaming.stateStore.providerClass"


def slices(events: DataFrame, parts: int = 4) -> str:
    """Cuts a log into files in the order of time; returns their directory."""
    path = shared_path(events.sparkSession)
    r = events.agg(F.min("event_id").alias("a"), F.max("event_id").alias("b")).first()
    width = max(1, ((r["b"] or 0) - (r["a"] or 0)) // parts + 1)
    for i in range(parts):
        lo = (r["a"] or 0) + i * width
        events.filter(F.col("event_id").between(lo, lo + width - 1)).coalesce(1).write.mode("append").parquet(path)
    return path


def source(spark: SparkSession, path: str, schema) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def run(stream: DataFrame, mode: str = "append", each: Callable[[DataFrame, int], None] | None = None) -> DataFrame:
    """Runs a stream over what its source holds; returns the rows it wrote. Recovery is by its checkpoint."""
    spark = stream.sparkSession
    out, mark = shared_path(spark), shared_path(spark)
    writer = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", mark)
    schema = stream.schema
    if each is not None:
        writer.foreachBatch(each).start().awaitTermination()
        return None
    if mode == "append":
        writer.format("parquet").option("path", out).start().awaitTermination()
    else:  # the last batch of a complete or update stream replaces what it repeats

        def put(batch: DataFrame, n: int) -> None:
            batch.withColumn("_batch", F.lit(n)).write.mode("append").parquet(out)

        writer.foreachBatch(put).start().awaitTermination()
        schema = T.StructType([*schema.fields, T.StructField("_batch", T.IntegerType())])
    spark.createDataFrame([], schema).write.mode("append").parquet(out)
    return spark.read.schema(schema).parquet(out)


def with_rocks(spark: SparkSession, f: Callable[[], DataFrame]) -> DataFrame:
    old = spark.conf.get(PROVIDER, None)
    spark.conf.set(PROVIDER, ROCKS)
    try:
        return f()
    finally:
        spark.conf.set(PROVIDER, old) if old else spark.conf.unset(PROVIDER)


def windowed(events: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """start, event_type, n, total by tumbling or sliding window; closed windows are emitted once."""
    w = F.window("ts", size, slide or size)
    g = events.withWatermark("ts", "1 hour").groupBy(w.alias("w"), "event_type")
    return g.agg(F.count("*").alias("n"), F.sum(F.col("value").cast("decimal(18,2)")).cast("double").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sessions(events: DataFrame, gap: str) -> DataFrame:
    g = events.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", gap).alias("w"), "user_id")
    return g.agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


class QueueState(StatefulProcessor):
    """A ring by host: occupancy and counts of pushes and pops; operations of a batch are replayed in the order of seq."""

    def __init__(self, capacity: int):
        self.capacity = capacity

    def init(self, handle) -> None:
        self.ends = handle.getValueState("ends", "head long, tail long")

    def handleInputRows(self, key, rows, timerValues):
        import pandas as pd

        head, tail = self.ends.get() if self.ends.exists() else (0, 0)
        ops = pd.concat(list(rows)).sort_values("seq")
        out = []
        for seq, op in zip(ops["seq"], ops["op"]):
            ok = tail - head < self.capacity if op == "push" else tail > head
            out.append((key[0], seq, op, ok, (tail if op == "push" else head) if ok else -1))
            tail, head = tail + (ok and op == "push"), head + (ok and op == "pop")
        self.ends.update((int(head), int(tail)))
        yield pd.DataFrame(out, columns=["host", "seq", "op", "ok", "pos"])

    def close(self) -> None:
        pass


def queue_stream(log: DataFrame, capacity: int) -> DataFrame:
    """``log``: host, seq, op. A failed operation has pos -1."""
    return log.groupBy("host").transformWithStateInPandas(QueueState(capacity), "host long, seq long, op string, ok boolean, pos long", "append", "none")


class FilterState(StatefulProcessor):
    """One 64-bit block of the filter; test and insert in the order of seq."""

    def init(self, handle) -> None:
        self.mask = handle.getValueState("mask", "mask long")

    def handleInputRows(self, key, rows, timerValues):
        import pandas as pd

        held = self.mask.get()[0] if self.mask.exists() else 0
        ops = pd.concat(list(rows)).sort_values("seq")
        out = []
        for seq, m in zip(ops["seq"], ops["mask"]):
            out.append((seq, bool(held & m == m)))
            held |= int(m)
        self.mask.update((int(held),))
        yield pd.DataFrame(out, columns=["seq", "present"])

    def close(self) -> None:
        pass


def filter_stream(keys: DataFrame, bloom: BlockedBloom) -> DataFrame:
    return bloom.keyed(keys).groupBy("block").transformWithStateInPandas(FilterState(), "seq long, present boolean", "append", "none")


class TableSink:
    """``foreachBatch`` target: each batch is folded and written under its id, so a repeated batch changes nothing."""

    def __init__(self, path: str):
        self.path = path

    def __call__(self, batch: DataFrame, n: int) -> None:
        batch.groupBy("key").agg(F.max_by("val", "seq").alias("val"), F.max("seq").alias("seq")).write.mode("overwrite").parquet(f"{self.path}/batch={n}")

    def state(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(self.path).groupBy("key").agg(F.max_by("val", "seq").alias("val"))


class IdleQueues(StatefulProcessor):
    """Emits a host once it has had no operation for ``idle_ms`` of event time."""

    def __init__(self, idle_ms: int):
        self.idle_ms = idle_ms

    def init(self, handle) -> None:
        self.handle = handle
        self.seen = handle.getValueState("seen", "ms long")

    def handleInputRows(self, key, rows, timerValues):
        import pandas as pd

        last = max(int(b["ms"].max()) for b in rows)
        if self.seen.exists():
            old = self.seen.get()[0]
            self.handle.deleteTimer(old + self.idle_ms)
            last = max(last, old)
        self.seen.update((last,))
        self.handle.registerTimer(last + self.idle_ms)
        yield pd.DataFrame({"host": [], "idle_since": []})

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo):
        import pandas as pd

        since = self.seen.get()[0]
        self.seen.clear()
        yield pd.DataFrame({"host": [key[0]], "idle_since": [since]})

    def close(self) -> None:
        pass


def idle_stream(log: DataFrame, idle_ms: int) -> DataFrame:
    """``log``: host, ts. host, idle_since (milliseconds) of queues that fell idle."""
    slim = log.withWatermark("ts", "0 seconds").select("host", "ts", F.unix_millis("ts").alias("ms"))
    return slim.groupBy("host").transformWithStateInPandas(IdleQueues(idle_ms), "host long, idle_since long", "append", "eventTime")


def late_rows(spark: SparkSession, path: str, schema, size: str) -> int:
    """Rows that a windowed sum dropped because they came after the watermark."""
    dropped = []
    q = windowed(source(spark, path, schema), size).writeStream.format("noop").outputMode("append").trigger(availableNow=True).option("checkpointLocation", shared_path(spark)).start()
    q.awaitTermination()
    for p in q.recentProgress:
        dropped += [s.numRowsDroppedByWatermark for s in p.stateOperators]
    return sum(dropped)


def join_static(stream: DataFrame, static: DataFrame, on: str) -> DataFrame:
    return stream.join(static, on)


def join_interval(left: DataFrame, right: DataFrame, within: str) -> DataFrame:
    """``left``: user_id, ts, event_id; ``right``: user_id, ts2, event_id2. Pairs whose right side follows within an interval."""
    a, b = left.withWatermark("ts", "1 hour").alias("a"), right.withWatermark("ts2", "1 hour").alias("b")
    cond = F.expr(f"a.user_id = b.user_id AND ts2 > ts AND ts2 <= ts + INTERVAL {within}")
    return a.join(b, cond).select(F.col("a.user_id").alias("user_id"), "event_id", "event_id2")


def distinct_stream(events: DataFrame, cols: list[str]) -> DataFrame:
    return events.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(cols)
