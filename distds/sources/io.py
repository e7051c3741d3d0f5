"""Tables in and out: explicit schemas, common formats, bucketed snapshots."""

from __future__ import annotations

import gc
import uuid

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema=None, **options) -> DataFrame:
    """CSV, JSON, text, ORC or Parquet; a schema is asked for where the files do not carry one."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", by: list[str] | None = None, mode: str = "errorifexists") -> None:
    writer = df.write.format(fmt).mode(mode)
    (writer.partitionBy(*by) if by else writer).save(path)


def snapshot(df: DataFrame, name: str, key: str, buckets: int) -> DataFrame:
    """A table bucketed and sorted by its key: later joins and merges on the key need no exchange of it."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(name)
    return df.sparkSession.table(name)


def shared_path(spark: SparkSession) -> str:
    """A new path in the folder that all executors share."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        import tempfile

        root = tempfile.mkdtemp(prefix="distds-")
        spark.sparkContext.setCheckpointDir(root)
    return f"{root}/distds-{uuid.uuid4().hex}"


def settle(df: DataFrame) -> DataFrame:
    """Write a table to the shared folder and read it back: cuts lineage, and a lost executor loses nothing."""
    path = shared_path(df.sparkSession)
    df.write.parquet(path)
    back = df.sparkSession.read.schema(df.schema).parquet(path)
    back._settled = path
    return back


def forget(spark: SparkSession, *tables: DataFrame) -> None:
    """Delete settled tables from which all that is needed is written, and let Spark delete unused shuffle files: these go when
    the driver's garbage is collected, which may be long after the query that wrote them."""
    for df in tables:
        path = spark._jvm.org.apache.hadoop.fs.Path(df._settled)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
    gc.collect()
    spark._jvm.System.gc()
