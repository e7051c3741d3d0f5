"""Streams over slices of the event log; each must equal its batch form."""

from __future__ import annotations

from pyspark.sql import functions as F

from distds.operators.bloom import BlockedBloom
from distds.queries.bloom import BLOCKS, K, ORACLES as FILTERS
from distds.queries.queues import HOSTS, MANY, replay_sql
from distds.queries.table import LAST
from distds.sources.io import shared_path, table
from distds.streaming import streams as st


def stream(spark, d, cols=None):
    e = table(spark, d, "events")
    e = e if cols is None else e.select(*cols)
    if "ts" in e.columns:  # watermarks need an instant
        e = e.withColumn("ts", F.col("ts").cast("timestamp"))
    return st.source(spark, st.slices(e), e.schema)


def st_tumbling(spark, d):
    """In update mode every window is out; the last value of each is kept."""
    w = st.run(st.windowed(stream(spark, d, ["ts", "event_type", "value", "event_id"]), "1 day"), "update")
    keep = w.groupBy("start", "event_type").agg(F.max_by(F.struct("n", "total"), "_batch").alias("v"))
    return keep.select("start", "event_type", F.col("v.n").alias("n"), F.col("v.total").alias("total"))


def st_sliding(spark, d):
    w = st.run(st.windowed(stream(spark, d, ["ts", "event_type", "value", "event_id"]), "2 days", "1 day"), "update")
    keep = w.groupBy("start", "event_type").agg(F.max_by(F.struct("n", "total"), "_batch").alias("v"))
    return keep.select("start", "event_type", F.col("v.n").alias("n"), F.col("v.total").alias("total"))


def st_append(spark, d):
    """In append mode a window is out once the watermark has passed its end."""
    return st.run(st.windowed(stream(spark, d, ["ts", "event_type", "value", "event_id"]), "1 day"))


def st_session(spark, d):
    out = st.run(st.sessions(stream(spark, d, ["ts", "user_id", "event_id"]), "2 hours"), "complete")
    last = out.agg(F.max("_batch")).first()[0]
    return out.filter(F.col("_batch") == last).drop("_batch")


def st_queue(spark, d):
    e = stream(spark, d, ["event_id", "user_id", "event_type"])
    op = F.when(F.col("event_type").isin("signup", "error"), "pop").otherwise("push")
    log = e.select((F.col("user_id") % HOSTS).alias("host"), F.col("event_id").alias("seq"), op.alias("op"))
    return st.with_rocks(spark, lambda: st.run(st.queue_stream(log, MANY)))


def st_bloom(spark, d):
    e = stream(spark, d, ["event_id", "user_id"]).select(F.col("event_id").alias("seq"), F.col("user_id").alias("x"))
    return st.with_rocks(spark, lambda: st.run(st.filter_stream(e, BlockedBloom(BLOCKS, K))))


def st_flush(spark, d):
    e = stream(spark, d, ["event_id", "user_id", "value"]).select(F.col("event_id").alias("seq"), F.col("user_id").alias("key"), F.col("value").alias("val"))
    sink = st.TableSink(shared_path(spark))
    st.run(e, each=sink)
    return sink.state(spark)


def st_dedup(spark, d):
    e = stream(spark, d, ["ts", "event_id"])
    return st.run(st.distinct_stream(e.union(e), ["event_id"])).select("event_id")


def st_static_join(spark, d):
    o = table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return st.run(st.join_static(stream(spark, d, ["event_id", "user_id"]), o, "user_id")).select("event_id", "c_mktsegment")


def st_interval_join(spark, d):
    """Purchases within an hour after a view of the same user."""
    e = stream(spark, d, ["ts", "event_id", "user_id", "event_type"])
    a = e.filter("event_type = 'view'").select("user_id", "ts", "event_id")
    b = e.filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("ts2"), F.col("event_id").alias("event_id2"))
    return st.run(st.join_interval(a, b, "1 HOUR"))


QUERIES = {f.__name__: f for f in (st_tumbling, st_sliding, st_append, st_session, st_queue, st_bloom, st_flush, st_dedup, st_static_join, st_interval_join)}
SUM = "count(*) AS n, sum(value::DECIMAL(18,2))::DOUBLE AS total"
ORACLES = {
    "st_tumbling": f"SELECT date_trunc('day', ts)::TIMESTAMP AS start, event_type, {SUM} FROM events GROUP BY ALL",
    "st_append": f"SELECT date_trunc('day', ts)::TIMESTAMP AS start, event_type, {SUM} FROM events WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY ALL",
    "st_sliding": f"SELECT (date_trunc('day', ts) - to_days(k))::TIMESTAMP AS start, event_type, {SUM} FROM events CROSS JOIN (SELECT unnest([0, 1]) AS k) GROUP BY ALL",
    "st_session": """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
        s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 2 HOUR AS "end", count(*) AS n FROM s GROUP BY user_id, k""",
    "st_queue": f"WITH RECURSIVE {replay_sql(HOSTS, MANY)} SELECT host, seq, op, ok, coalesce(pos, -1) AS pos FROM out",
    "st_bloom": FILTERS["bb_insert"],
    "st_flush": LAST,
    "st_static_join": "SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id",
    "st_interval_join": "SELECT a.user_id, a.event_id, b.event_id AS event_id2 FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'",
    "st_dedup": "SELECT event_id FROM events",
}
