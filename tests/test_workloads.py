"""Sorting, k-mers, contigs and streams against brute force on small inputs."""

import os
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from conftest import SMALL
from pyspark.sql import functions as F

from distds.operators.bloom import BlockedBloom
from distds.plans import contigs, kmers, micro, sorting
from distds.sources import io
from distds.streaming import streams as st


def reads(spark, *seqs):
    return spark.createDataFrame(list(enumerate(seqs)), "read_id long, seq string")


def test_extract_against_python(spark):
    long = "ACGTTGCAAC" * 160
    seqs = ["", "AC", "ACGTA", long]
    got = sorted((r["read_id"], r["p"], r["kmer"], r["left"] or "", r["right"] or "") for r in kmers.extract(reads(spark, *seqs), 5).collect())
    want = sorted((i, p + 1, s[p : p + 5], s[p - 1] if p else "", s[p + 5] if p + 5 < len(s) else "") for i, s in enumerate(seqs) for p in range(len(s) - 4))
    assert got == want


def test_counts_agree(spark):
    r = reads(spark, "ACGTACGTAC", "GTACGTTTTT", "CCCCA")
    x = kmers.extract(r, 3)
    want = Counter(s[i : i + 3] for s in ("ACGTACGTAC", "GTACGTTTTT", "CCCCA") for i in range(len(s) - 2))
    assert {k["kmer"]: k["n"] for k in kmers.count_plain(x).collect()} == want
    many = {k: n for k, n in want.items() if n > 1}
    for blocks in (1, 4, 1024):
        assert {k["kmer"]: k["n"] for k in kmers.count_two_level(x, blocks).collect()} == many
        for row in kmers.count_bloom(x, blocks).collect():
            assert row["hits"] + 1 - row["fp"] == want[row["kmer"]] == row["occ"]
        assert {k["kmer"]: k["n"] for k in kmers.count_bloom(x, blocks, exact=True).collect()} == many
    assert {k["kmer"]: k["n"] for k in kmers.count_two_level(x).collect()} == many
    for parts in (1, 4):
        assert {k["kmer"]: k["n"] for k in kmers.count_localised(x, parts, 3).collect()} == many
    got = kmers.filter_report(x, 3, 1024).first()
    assert got["all_entries"] == len(want) and got["kept_sightings"] >= sum(many.values()) and got["kept_entries"] >= len(many) and kmers.sightings(r, 3) == sum(want.values())


def test_masks_of_many_chunks_merge():
    """Bits that two sightings set, whatever chunk and batch they lie in."""
    rng = np.random.default_rng(4)
    block, mask = rng.integers(5, 9, 400), np.int64(1) << rng.integers(0, 64, 400)
    ids, _, want = kmers.fold_masks(block, mask)
    parts = []
    for some in np.array_split(rng.permutation(400), 7):
        parts.append(pa.RecordBatch.from_arrays([pa.array(x) for x in kmers.fold_masks(block[some], mask[some])], names=["block", "one", "two"]))
    got = pa.Table.from_batches(list(kmers.merge_masks([parts[0], pa.Table.from_batches(parts[1:]).combine_chunks().to_batches()[0]])))
    assert dict(zip(got["block"].to_pylist(), got["two"].to_pylist())) == {i: t for i, t in zip(ids.tolist(), want.tolist()) if t}


def graph(spark, k, *seqs):
    n = io.settle(contigs.nodes(kmers.extract(reads(spark, *seqs), k)))
    return n, io.settle(contigs.edges(n))


def test_ring_is_emitted_once(spark):
    ring = "ACGGTCATTG"
    s = ring + ring[:4] + ring[4:6]
    n, e = graph(spark, 4, s, s)
    assert contigs.heads(n, e).count() == 0
    for out in (contigs.walk_components(n, e), contigs.assemble(contigs.double(n.select(F.col("kmer").alias("node")), e), F.expr("substring(node, -1)"))):
        got = [r["contig"] for r in out.collect()]
        assert len(got) == 1 and len(got[0]) == 4 + len(ring) - 1 and got[0][:4] == min(r["kmer"] for r in n.collect())
    assert [(r["contig"], r["copies"]) for r in contigs.all_seeds(n, e).collect()] == [(got[0], len(ring))]
    assert contigs.double(n.select(F.col("kmer").alias("node")), e, cycles="drop").count() == 0


def test_fork_stops_contigs(spark):
    a, b = "AACCGTTAGC", "TTCCGTTACA"
    n, e = graph(spark, 4, a, a, b, b)
    walked = sorted(r["contig"] for r in contigs.walk(n, e).collect())
    doubled = sorted(r["contig"] for r in contigs.assemble(contigs.double(n.select(F.col("kmer").alias("node")), e), F.expr("substring(node, -1)")).collect())
    assert walked == doubled and sum(len(c) - 3 for c in walked) == n.count()
    assert "CCGTTA" in walked
    seeds = contigs.all_seeds(n, e).collect()
    assert sorted(r["contig"] for r in seeds) == walked and all(r["copies"] == len(r["contig"]) - 3 for r in seeds)
    with pytest.raises(RuntimeError):
        contigs.walk(n, e, steps=1)


def test_specialised_and_generic_agree(spark):
    x = kmers.extract(reads(spark, *["ACGGTCATTGACCA"] * 2, *["TTGACCAGGA"] * 2), 5)
    a = sorted(r["contig"] for r in contigs.contigs_specialised(x, 5).collect())
    assert a == sorted(r["contig"] for r in contigs.contigs_generic(x).collect()) == sorted(r["contig"] for r in contigs.contigs_double(x).collect())
    assert contigs.stats(contigs.contigs_specialised(x, 5)).first()["contigs"] == len(a)


@pytest.mark.parametrize("buckets", [1, 3, 8])
def test_sort_by_any_number_of_buckets(spark, buckets):
    keys = spark.range(500).select(F.pmod(F.col("id") * 7919 * 4099, F.lit(sorting.KEY_RANGE)).alias("key"))
    want = sorted(r["key"] for r in keys.collect())
    got = [r["key"] for r in sorting.global_rank(sorting.sort_bucketed(keys, buckets)).orderBy("pos").collect()]
    assert got == want
    assert [r["key"] for r in sorting.global_rank(sorting.sort_skew(keys, "key", buckets)).orderBy("pos").collect()] == want


def test_io_formats(spark, tmp_path):
    df = spark.range(5).select("id", F.col("id").cast("string").alias("s"))
    for fmt in ("parquet", "orc", "json", "csv"):
        io.write(df, str(tmp_path / fmt), fmt)
        assert io.read(spark, str(tmp_path / fmt), fmt, df.schema).count() == 5
    with pytest.raises(ValueError):
        io.read(spark, str(tmp_path / "csv"), "csv")


def test_stream_resumes_and_repeats_nothing(spark, tmp_path):
    e = io.table(spark, SMALL, "events").select(F.col("event_id"), F.col("event_id").alias("seq"), F.col("user_id").alias("key"), F.col("value").alias("val"))
    path = st.slices(e)
    sink = st.TableSink(str(tmp_path / "state"))
    s = st.source(spark, path, e.schema)
    for _ in range(2):  # the second run finds nothing new
        s.writeStream.option("checkpointLocation", str(tmp_path / "mark")).trigger(availableNow=True).foreachBatch(sink).start().awaitTermination()
    once = sorted(os.listdir(tmp_path / "state"))
    sink(e.limit(0), 99)
    want = {r["key"]: r["val"] for r in e.groupBy("key").agg(F.max_by("val", "seq").alias("val")).collect()}
    assert {r["key"]: r["val"] for r in sink.state(spark).collect()} == want and len(once) == 4


def test_filter_stream_equals_batch(spark):
    e = io.table(spark, SMALL, "events").select("event_id", F.col("event_id").alias("seq"), F.col("user_id").alias("x"))
    bloom = BlockedBloom(8)
    s = st.source(spark, st.slices(e), e.schema).select("seq", "x")
    got = st.with_rocks(spark, lambda: st.run(st.filter_stream(s, bloom)))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, bloom.insert(e.select("seq", "x")).collect()))


def test_contraction_equals_doubling(spark):
    s = "ACGGTCATTGACCATTTGACAGGCATCAGT"
    ring = "AAGCTTCGTA"
    n, e = graph(spark, 5, s, s, ring + ring, ring + ring)
    for parts in (1, 3):
        a = contigs.contract(n, e, m=3, parts=parts)
        assert a.count() == n.count()
    a = contigs.double_contracted(n, e)
    b = contigs.double(n.select(F.col("kmer").alias("node")), e)
    assert sorted(map(tuple, a.select("node", "head", "dist").collect())) == sorted(map(tuple, b.collect()))


def test_late_rows_are_counted(spark, tmp_path):
    schema = "ts timestamp, event_type string, value double, event_id long"
    path = str(tmp_path / "late")
    for i, day in enumerate(("2024-01-01 00:00:00", "2024-01-05 00:00:00", "2024-01-06 00:00:00", "2024-01-01 01:00:00")):
        df = spark.createDataFrame([(day, "view", 1.0, i)], "ts string, event_type string, value double, event_id long")
        df.withColumn("ts", F.to_timestamp("ts")).coalesce(1).write.mode("append").parquet(path)
    schema = spark.read.parquet(path).schema
    assert st.late_rows(spark, path, schema, "1 hour") == 1


def test_idle_queues_expire(spark, tmp_path):
    path = str(tmp_path / "ops")
    for rows in ([(1, "2024-01-01 00:00:00"), (2, "2024-01-01 00:00:00")], [(2, "2024-01-01 05:00:00")], [(2, "2024-01-01 05:30:00")]):
        df = spark.createDataFrame(rows, "host long, ts string").withColumn("ts", F.to_timestamp("ts"))
        df.coalesce(1).write.mode("append").parquet(path)
    s = st.source(spark, path, spark.read.parquet(path).schema)
    got = st.with_rocks(spark, lambda: st.run(st.idle_stream(s, 3_600_000)))
    assert 1 in [r["host"] for r in got.collect()]


def test_program_lengths():
    found = micro.program_lengths()
    assert {"sort_bucketed", "contigs_double", "contigs_specialised", "count_two_level"} <= set(found) and min(found.values()) > 1
