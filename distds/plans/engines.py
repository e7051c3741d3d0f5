"""One operation on four execution engines with equal results: positions of pushes on many hosts."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

SCHEMA = "host long, seq long, pos long"


def on_dataframe(log: DataFrame) -> DataFrame:
    return log.select("host", "seq", (F.row_number().over(Window.partitionBy("host").orderBy("seq")) - 1).cast("long").alias("pos"))


def on_sql(log: DataFrame) -> DataFrame:
    return log.sparkSession.sql("SELECT host, seq, CAST(row_number() OVER (PARTITION BY host ORDER BY seq) - 1 AS BIGINT) AS pos FROM {log}", log=log)


def on_rdd(log: DataFrame) -> DataFrame:
    """Composite keys sorted in the shuffle; a running count inside each partition."""

    def number(rows):
        host, n = None, 0
        for (h, s), _ in rows:
            n = n + 1 if h == host else 0
            host = h
            yield h, s, n

    keyed = log.select("host", "seq").rdd.map(lambda r: ((r[0], r[1]), None))
    placed = keyed.repartitionAndSortWithinPartitions(log.sparkSession.sparkContext.defaultParallelism, lambda k: hash(k[0]))
    return log.sparkSession.createDataFrame(placed.mapPartitions(number), SCHEMA)


def on_arrow(log: DataFrame) -> DataFrame:
    def number(t: pa.Table) -> pa.Table:
        t = t.sort_by("seq")
        return pa.table({"host": t.column("host"), "seq": t.column("seq"), "pos": pa.array(range(len(t)), pa.int64())})

    return log.select("host", "seq").groupBy("host").applyInArrow(number, SCHEMA)


ENGINES = {"dataframe": on_dataframe, "sql": on_sql, "rdd": on_rdd, "arrow": on_arrow}
