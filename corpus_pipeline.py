"""A corpus pipeline of five stages: quality, line dedup, near duplicates, source mix, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from distds.llm import jaccard, linededup, mixing, packing, quality, screen
from distds.llm.queries import quality_weights
from distds.llm.scratch import Scratch

#: The classifier rejects below this score; lower than the report's 0.3, as a clean document lost costs more than a bad one kept.
REJECT = 0.2
COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents that the classifier, trained on the labels, does not reject; empty ones are rejected."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", F.col("quality").alias("y"))
    weights = quality.fit(docs, labels)
    kept = quality.score(docs.select(*COLUMNS), weights).filter((F.col("score") >= REJECT) & F.col("text").rlike(r"[^\x20\x09-\x0D]"))
    return kept.select(*COLUMNS)


def without_boilerplate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops lines that stand on too large a share of a source's distinct texts; copies count once, a document of nothing else stays."""
    clean = linededup.dedup_lines(docs.select(*COLUMNS), F.col("source"), once=True)
    clean = clean.withColumn("n_chars", F.length("text").cast("long"))
    return clean.filter(F.col("text").rlike(r"[^\x20\x09-\x0D]")).select(*COLUMNS)


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest doc_id of each group of near copies (five words, similarity 0.8).

    Null doc_ids come last; a hash of the row decides between different texts of one doc_id or of none.
    """
    docs = docs.select(*COLUMNS)
    groups = jaccard.similar_groups(docs, group=True)
    key = [F.col("row").alias("key"), F.col("row2").alias("key2")]
    first = F.min(F.struct(F.col("doc_id").isNull().alias("blank"), "doc_id", "row", "row2"))
    best = groups.filter("group is not null").groupBy("group").agg(first.alias("best"), F.count("*").alias("n")).filter("n > 1")
    best = Scratch(spark).stash(best.select("group", F.col("best.row").alias("stays"), F.col("best.row2").alias("stays2")))
    members = groups.filter("group is not null").select("group", "row", "row2").distinct()
    gone = members.join(best, "group").filter("row != stays or row2 != stays2").select(*key)
    rows = screen.anti(docs.withColumn("key", F.xxhash64("doc_id", "text")).withColumn("key2", F.xxhash64("text", "doc_id")), gone, also=("key2",))
    twice = groups.filter(F.col("sig").isNotNull()).groupBy(*key).count().filter("count > 1").select("key", "key2")
    twice = Scratch(spark).stash(twice)
    if not twice.head(1):
        return rows.select(*COLUMNS)
    again = screen.semi(rows, twice, also=("key2",)).dropDuplicates(["key", "key2"])  # rows repeated with their doc_id: one stays
    return screen.anti(rows, twice, also=("key2",)).unionByName(again).select(*COLUMNS)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as many times as the mix takes it.

    Documents without words are not taken; a null source is a source of its own; repeated rows are taken alike; an empty table
    gives an empty one; other columns are dropped.
    """
    docs = docs.select(*COLUMNS).withColumn("_row", F.xxhash64("doc_id", "text")).withColumn("_row2", F.xxhash64("text", "doc_id"))
    counts = mixing.mix(docs, quality=quality_weights(spark, sf_dir), keep=("_row", "_row2"))
    counts = Scratch(spark).stash(counts.filter("copies > 0").groupBy("_row", "_row2").agg(F.max("copies").alias("copies")))
    taken = docs.join(counts, ["_row", "_row2"])
    return taken.withColumn("_i", F.explode(F.sequence(F.lit(1), F.col("copies")))).select(*COLUMNS)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in bins. Null and empty texts make no piece; texts longer than a bin make several; repeated rows
    are packed one by one; an empty table gives no rows; columns other than doc_id and text do not matter."""
    return packing.best_fit(docs)


STAGES = [
    ("quality classifier", good_quality),
    ("line dedup", without_boilerplate),
    ("n-gram Jaccard join", without_near_copies),
    ("mixing", mixed),
    ("best-fit packing", packed),
]

#: The classifier and the packer have no SQL form; the stages are tested against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES:
        docs = scratch.stash(stage(spark, docs, sf_dir))
    return docs
