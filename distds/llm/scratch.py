"""Shared helpers: tables in the cluster's shared folder and two-level running totals."""

from __future__ import annotations

import gc

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from distds.sources.io import shared_path

#: Words are maximal runs of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


class Scratch:
    """Tables written once to the shared folder and read back: short lineage, known sizes, safe against lost executors."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.base = shared_path(spark)
        self.n = 0

    def stash(self, df: DataFrame) -> DataFrame:
        self.n += 1
        path = f"{self.base}/{self.n}"
        df.write.parquet(path)
        back = self.spark.read.schema(df.schema).parquet(path)
        back._scratch_path = path
        return back

    def drop(self, *tables: DataFrame) -> None:
        """Delete stashed tables once everything made from them is written, and let Spark delete unused shuffle files."""
        for df in tables:
            path = self.spark._jvm.org.apache.hadoop.fs.Path(df._scratch_path)
            path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)
        self.tidy()

    def tidy(self) -> None:
        """Shuffle files go when the driver's garbage is collected, which may be long after the query that wrote them."""
        gc.collect()
        self.spark._jvm.System.gc()


def only(df: DataFrame, *names: str) -> DataFrame:
    """The named columns, whatever others there are: a clash in case or a repeated name is settled for the exact, first one."""
    at: dict[str, int] = {}
    for i, c in enumerate(df.columns):
        if c in names and c not in at:
            at[c] = i
    return df.toDF(*[c if at.get(c) == i else f"_other_{i}" for i, c in enumerate(df.columns)]).select(*names)


def fresh(df: DataFrame, name: str) -> str:
    """A column name that is not taken."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def ascii_lower(c: Column) -> Column:
    """Lower-case A-Z and nothing else."""
    return F.translate(c, UPPER, LOWER)


def word_count(c: Column) -> Column:
    return F.regexp_count(F.coalesce(c, F.lit("")), F.lit(WORD)).cast("long")


def unit(c: Column) -> Column:
    """A 64-bit hash as a number in (0, 1)."""
    return (F.shiftrightunsigned(c, 12).cast("double") + 0.5) / float(1 << 52)


def bucket_count(rows: int, per_bucket: int = 50_000, least: int = 64) -> int:
    return max(least, -(-rows // per_bucket))


def running_total(df: DataFrame, value: str, order: list, part: list[str], bucket: str, out: str) -> DataFrame:
    """Adds ``out``: the sum of ``value`` over the rows before, in the order (``bucket``, ``order``) within ``part``.

    Two levels: sums by (part, bucket) are added up in a small table and only rows of one bucket meet in a window, so
    no task gets a whole part. ``bucket`` must not be null and must not fall as the order grows.
    """
    sums = df.groupBy(*part, bucket).agg(F.sum(value).alias("_s"))
    w = Window.partitionBy(*part).orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select(*part, bucket, F.coalesce(F.sum("_s").over(w), F.lit(0)).alias("_before"))
    inner = Window.partitionBy(*part, bucket).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    rows = df.withColumn("_in", F.coalesce(F.sum(value).over(inner), F.lit(0)))
    return rows.join(offsets, [*part, bucket]).withColumn(out, F.col("_before") + F.col("_in")).drop("_before", "_in")
