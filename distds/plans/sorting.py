"""Integer sort of keys with a known uniform range, and the baselines it is compared with."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from distds.functions.hashing import h60
from distds.sources.io import settle, shared_path

KEY_RANGE = 1 << 27


def line_key() -> Column:
    """A uniform key in [0, KEY_RANGE) of each lineitem row."""
    cents = F.round(F.col("l_extendedprice") * 100).cast("long")
    return F.pmod(h60(F.concat_ws("#", *[F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")], cents.cast("string"))), F.lit(KEY_RANGE))


def sort_keys(lines: DataFrame) -> DataFrame:
    return lines.select(line_key().alias("key"))


def bucket_of(key: Column, buckets: int) -> Column:
    """The owner of a key, from the known range alone: no sampling job."""
    return F.floor(key / -(-KEY_RANGE // buckets)).cast("int")


def _ranked(df: DataFrame) -> DataFrame:
    """bucket, rank in bucket, key: local order of each bucket. Rows dealt by bucket id stay where they are."""
    return df.withColumn("rank", F.row_number().over(Window.partitionBy("bucket").orderBy("key")))


def dealt(keys: DataFrame, buckets: int) -> DataFrame:
    """The one exchange: every bucket to the partition of its own number."""
    return keys.withColumn("bucket", bucket_of(F.col("key"), buckets)).repartitionById(buckets, "bucket")


def global_rank(df: DataFrame) -> DataFrame:
    """key, pos: the local rank plus what smaller buckets hold (one row for each bucket).

    The buckets' sizes come from the ranks, so both sides read one and the same exchange of keys.
    """
    counts = df.groupBy("bucket").agg(F.max("rank").alias("n"))
    before = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    offs = counts.select("bucket", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("off"))
    return df.join(F.broadcast(offs), "bucket").select("key", (F.col("off") + F.col("rank")).cast("long").alias("pos"))


def sort_bucketed(keys: DataFrame, buckets: int = 8) -> DataFrame:
    """One exchange to the bucket's owner, then a local sort."""
    return _ranked(dealt(keys, buckets))


def sort_bulk_sync(keys: DataFrame, buckets: int = 8) -> DataFrame:
    """Two strict steps: all keys are dealt and written, a folder for each bucket, before any bucket is read and sorted."""
    path = shared_path(keys.sparkSession)
    dealt(keys, buckets).write.partitionBy("bucket").parquet(path)
    read = keys.sparkSession.read.schema("key long, bucket int").parquet(path)
    return _ranked(read.repartitionById(buckets, "bucket"))


def sort_pipelined(keys: DataFrame, buckets: int = 8) -> DataFrame:
    """Exchange by owner id, sorted within partitions as rows arrive; nothing is written in between."""
    return dealt(keys, buckets).sortWithinPartitions("bucket", "key")


def sort_global(keys: DataFrame) -> DataFrame:
    """A sort without knowledge of the range: Spark samples it first. key, bucket (the sampled range) and rank in it."""
    place = F.monotonically_increasing_id()  # the range in the upper bits, the row in it below
    return settle(keys.orderBy("key").select("key", F.shiftright(place, 33).cast("int").alias("bucket"), (place.bitwiseAND(F.lit((1 << 33) - 1)) + 1).alias("rank")))


def splitters(df: DataFrame, col: str, buckets: int) -> list:
    """Equal-depth splitters from an approximate quantile sketch of all rows."""
    got = df.agg(F.percentile_approx(col, [i / buckets for i in range(1, buckets)], 10_000)).first()[0]
    return sorted(set(got or []))


def sort_skew(df: DataFrame, col: str, buckets: int = 8) -> DataFrame:
    """For keys of unknown, uneven distribution: splitters first, then as :func:`sort_bucketed`."""
    bucket = F.lit(0)
    for s in splitters(df, col, buckets):
        bucket = bucket + (F.col("key") >= F.lit(s)).cast("int")
    return _ranked(df.select(F.col(col).alias("key")).withColumn("bucket", bucket).repartitionById(buckets, "bucket"))


def messages(keys: DataFrame, sources: int, buckets: int, sizes: tuple[int, ...]) -> DataFrame:
    """message_size, pairs, msgs, most: messages by source and destination for several message sizes."""
    k = F.col("key")
    pairs = keys.select(F.pmod(h60(k, 7), F.lit(sources)).alias("src"), bucket_of(k, buckets).alias("dst")).groupBy("src", "dst").agg(F.count("*").alias("n"))
    sized = pairs.select("n", F.explode(F.array(*[F.lit(s) for s in sizes])).alias("message_size"))
    m = F.ceil(F.col("n") / F.col("message_size"))
    return sized.groupBy("message_size").agg(F.count("*").cast("long").alias("pairs"), F.sum(m).cast("long").alias("msgs"), F.max(m).cast("long").alias("most"))
