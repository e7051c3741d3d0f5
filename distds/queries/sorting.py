"""Integer sort of line keys."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from distds.functions.hashing import h60_sql
from distds.plans import sorting as s
from distds.sources.io import table

SIZES = (16, 64, 256, 1024, 4096)


def keys(spark, d):
    return s.sort_keys(table(spark, d, "lineitem"))


def isort_bucketed(spark, d):
    return s.global_rank(s.sort_bucketed(keys(spark, d)))


def isort_bulk_sync(spark, d):
    return s.global_rank(s.sort_bulk_sync(keys(spark, d)))


def isort_pipelined(spark, d):
    rows = s.sort_pipelined(keys(spark, d))
    return s.global_rank(rows.withColumn("rank", F.row_number().over(Window.partitionBy("bucket").orderBy("key"))))


def isort_global(spark, d):
    """The sampled global order; ranks come from the sampled ranges and their sizes."""
    return s.global_rank(s.sort_global(keys(spark, d)))


def isort_skew(spark, d):
    cents = table(spark, d, "lineitem").select(F.round(F.col("l_extendedprice") * 100).cast("long").alias("cents"))
    return s.global_rank(s.sort_skew(cents, "cents"))


def isort_messages(spark, d):
    return s.messages(keys(spark, d), 16, 8, SIZES)


QUERIES = {f.__name__: f for f in (isort_bucketed, isort_bulk_sync, isort_pipelined, isort_global, isort_skew, isort_messages)}
KEY = h60_sql("l_orderkey || '#' || l_linenumber || '#' || l_partkey || '#' || l_suppkey || '#' || round(l_extendedprice * 100)::BIGINT") + f" % {s.KEY_RANGE}"
RANK = f"SELECT {KEY} AS key, row_number() OVER (ORDER BY {KEY}) AS pos FROM lineitem"
ORACLES = {
    **{q: RANK for q in ("isort_bucketed", "isort_bulk_sync", "isort_pipelined", "isort_global")},
    "isort_skew": "SELECT round(l_extendedprice * 100)::BIGINT AS key, row_number() OVER (ORDER BY round(l_extendedprice * 100)::BIGINT) AS pos FROM lineitem",
    "isort_messages": f"""WITH k AS (SELECT {KEY} AS key FROM lineitem), p AS (SELECT {h60_sql('key', 7)} % 16 AS src, key // {s.KEY_RANGE // 8} AS dst, count(*) AS n FROM k GROUP BY ALL),
        m AS (SELECT unnest([{', '.join(map(str, SIZES))}])::INT AS message_size) SELECT message_size, count(*) AS pairs, sum(ceil(n / message_size))::BIGINT AS msgs, max(ceil(n / message_size))::BIGINT AS most FROM p CROSS JOIN m GROUP BY 1""",
}
