"""Joins and helpers around the structures that Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(points: DataFrame, ranges: DataFrame, x: str, lo: str, hi: str, width: float) -> DataFrame:
    """Pairs with ``lo <= x < hi``: ranges are listed by cells of ``width``, so an equi-join finds them."""
    cell = F.floor(F.col(x) / width)
    spread = F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width)))
    both = points.withColumn("_cell", cell).join(ranges.withColumn("_cell", spread), "_cell")
    return both.filter((F.col(x) >= F.col(lo)) & (F.col(x) < F.col(hi))).drop("_cell")


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, value: str, out: str) -> DataFrame:
    """For each left row the last right ``value`` strictly before it: union and one window, no pairs."""
    both = left.select(by, at, F.lit(1).alias("_l"), F.lit(None).cast(right.schema[value].dataType).alias("_v")).unionByName(right.select(by, at, F.lit(0).alias("_l"), F.col(value).alias("_v")))
    before = Window.partitionBy(by).orderBy(at).rangeBetween(Window.unboundedPreceding, -1)
    return both.withColumn(out, F.last("_v", ignorenulls=True).over(before)).filter("_l = 1").select(by, at, out)


def top_by(df: DataFrame, by: str, order: list[Column], k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(by).orderBy(*order))).filter(F.col("rank") <= k)


def strip_tags(html: Column) -> Column:
    return F.regexp_replace(html, "<[^>]*>", "")
