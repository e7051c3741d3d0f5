"""Table functions for SQL."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


def register(spark: SparkSession) -> None:
    """``kmers(text, k)``: place and k-mer of each window of a text."""

    class Kmers:
        def eval(self, text: str, k: int):
            for p in range(len(text or "") - k + 1):
                yield p + 1, text[p : p + k]

    spark.udtf.register("kmers", udtf(Kmers, returnType="p: int, kmer: string"))
