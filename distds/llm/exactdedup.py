"""Exact dedup against immutable snapshots screened by static filters.

The corpus arrives in generations; each is an immutable snapshot once it is in. For every snapshot and digest bucket a
binary-fuse filter is built once and kept as a table. Digests of a later generation probe the filters of all earlier ones:
what no filter knows is new and is grouped within its own generation; what a filter may know joins the exact digest bucket of
that snapshot. Members of every group found are then compared with their keeper byte by byte.

Edge cases: null texts count as empty; of equal texts the row with the largest doc_id stays, null doc_ids last; rows that repeat
the keeper's doc_id are told apart by an arbitrary order, so one row stays in every group; empty tables give no rows; other
columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from distds.llm import fuse, screen
from distds.llm.scratch import Scratch, ascii_lower, bucket_count, only

#: Digests of one snapshot in one filter, about.
PER_FILTER = 200_000


def words64(digests: pa.ChunkedArray) -> np.ndarray:
    """The first eight bytes of 32-byte digests."""
    raw = digests.combine_chunks()
    if isinstance(raw, pa.ChunkedArray):
        raw = pa.concat_arrays(raw.chunks) if raw.num_chunks else pa.array([], pa.binary())
    offs = np.frombuffer(raw.buffers()[1], dtype=np.int32)[raw.offset : raw.offset + len(raw) + 1]
    data = np.frombuffer(raw.buffers()[2], dtype=np.uint8)
    return np.ascontiguousarray(data[offs[:-1, None] + np.arange(8)]).view(np.uint64).ravel() if len(raw) else np.zeros(0, np.uint64)


def build_filter(table: pa.Table) -> pa.Table:
    keys = words64(table.column("digest"))
    return pa.table({"bucket": pa.array([table.column("bucket")[0].as_py()], pa.int32()), "gen": pa.array([table.column("gen")[0].as_py()], pa.int32()), "filter": pa.array([fuse.build(keys)], pa.binary())})


def probe(left: pa.Table, right: pa.Table) -> pa.Table:
    """For each incoming digest, the earlier snapshots whose filter may hold it."""
    keys, gens = words64(left.column("digest")), left.column("gen").to_numpy()
    rows, snaps = [], []
    for g, blob in zip(right.column("gen").to_pylist(), right.column("filter").to_pylist()):
        hit = np.flatnonzero((gens > g) & fuse.contains(blob, keys))
        rows.append(hit)
        snaps.append(np.full(len(hit), g, np.int32))
    at = np.concatenate(rows) if rows else np.zeros(0, np.int64)
    out = left.select(["digest", "gen"]).take(pa.array(at))
    return out.append_column("snapshot", pa.array(np.concatenate(snaps) if snaps else np.zeros(0, np.int32)))


def exact_dedup(docs: DataFrame, generation: Column, normalise=ascii_lower, most: int = screen.MOST, also: tuple = ()) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256, seen_before (an earlier snapshot holds the text) for every row.

    ``generation``: int, the batch a row came with, from doc_id, text or the columns ``also``; earlier batches are snapshots to later ones.
    """
    scratch = Scratch(docs.sparkSession)
    docs = only(docs, "doc_id", "text", *also)
    text = normalise(F.coalesce(F.col("text"), F.lit("")))
    slim = docs.select("doc_id", generation.cast("int").alias("gen"), F.sha2(text, 256).alias("text_sha256"))
    rows = scratch.stash(slim.withColumn("digest", F.unhex("text_sha256")))
    entries = rows.groupBy("digest", "gen").agg(F.count("*").alias("n"), F.max("doc_id").alias("top"))
    b = bucket_count(rows.count(), PER_FILTER, 16)
    entries = scratch.stash(entries.withColumn("bucket", F.pmod(F.xxhash64("digest"), F.lit(b)).cast("int")))

    last = entries.agg(F.max("gen")).first()[0] or 0
    filters_table = scratch.stash(entries.filter(F.col("gen") < last).groupBy("bucket", "gen").applyInArrow(build_filter, "bucket int, gen int, filter binary"))
    incoming = entries.select("digest", "gen", "bucket")
    maybe = incoming.groupBy("bucket").cogroup(filters_table.groupBy("bucket")).applyInArrow(probe, "digest binary, gen int, snapshot int")
    known = entries.select("digest", F.col("gen").alias("snapshot"))
    seen = scratch.stash(maybe.join(known, ["digest", "snapshot"]).select("digest", "gen").distinct())  # exact buckets

    # A text no earlier snapshot holds opens a group, in the generation where it is first met; later ones join it.
    entries = entries.join(seen.withColumn("seen_before", F.lit(True)), ["digest", "gen"], "left").withColumn("seen_before", F.coalesce("seen_before", F.lit(False)))
    groups = scratch.stash(entries.groupBy("digest").agg(F.sum("n").alias("group_size"), F.max("top").alias("keep_id"), F.min(F.when(~F.col("seen_before"), F.col("gen"))).alias("born")).filter("group_size > 1"))

    # Byte checks: every member of a group against the text of its keeper; texts of no group are screened out where they lie.
    texts = docs.select("doc_id", text.alias("norm")).withColumn("digest", F.unhex(F.sha2("norm", 256))).withColumn("key", F.xxhash64("digest"))
    filters = screen.screen(groups.select(F.xxhash64("digest").alias("key")).distinct(), most)
    members = scratch.stash(screen.screened(texts, filters).join(groups.select("digest", "keep_id"), "digest"))
    keeper = members.filter(F.col("doc_id").eqNullSafe(F.col("keep_id"))).select("digest", F.col("norm").alias("kept_norm"))
    keeper = scratch.stash(keeper.dropDuplicates(["digest"]))  # written, so that the join can split a hot group
    odd = members.join(keeper, "digest").filter(F.col("norm") != F.col("kept_norm")).select("digest")
    if odd.head(1):
        raise ValueError("two different texts share a SHA-256 digest")
    scratch.drop(members, keeper, filters_table)

    marked = rows.join(groups, "digest", "left")
    marked = marked.withColumn("seen_before", F.coalesce(F.col("gen") > F.col("born"), F.lit(False)))
    marked = marked.withColumn("group_size", F.coalesce("group_size", F.lit(1)).cast("long")).withColumn("keep_id", F.when(F.col("born").isNull(), F.col("doc_id")).otherwise(F.col("keep_id")))
    top = F.col("doc_id").eqNullSafe(F.col("keep_id"))
    twice = rows.filter("doc_id is not null").groupBy("digest", "doc_id").count().filter("count > 1").select("digest", F.col("doc_id").alias("keep_id"))
    blank = rows.filter("doc_id is null").groupBy("digest").count().filter("count > 1").select("digest", F.lit(None).cast("long").alias("keep_id"))
    tops = groups.select("digest", "keep_id").join(twice.union(blank).withColumnRenamed("keep_id", "k").withColumnRenamed("digest", "d"), F.col("digest").eqNullSafe(F.col("d")) & F.col("keep_id").eqNullSafe(F.col("k")))
    tops = scratch.stash(tops.select("digest", F.lit(True).alias("tops")))
    repeated = marked.join(tops.select("digest"), "digest", "left_semi").filter(top)
    first = F.row_number().over(Window.partitionBy("digest").orderBy("gen")) == 1
    names = ("doc_id", "keep_id", "group_size", "kept", "text_sha256", "seen_before")
    plain = marked.join(tops, "digest", "left").filter(F.col("tops").isNull() | ~top).withColumn("kept", top)
    return plain.select(*names).union(repeated.withColumn("kept", first).select(*names))
