"""Stretches of reads against plain k-mers, what they move, and tables that outgrow their slots."""

import random
import time

import pyarrow as pa
import pytest
from conftest import SMALL
from pyspark.sql import functions as F

from distds import queries as core
from distds.operators.keyed_table import KeyedTable
from distds.plans import contigs, kmers, stretches

RING = "ACGGTCATTGACCAGTTCGGAGC"
SEEDED = random.Random(5)
READS = ["".join(SEEDED.choice("ACGT") for _ in range(200)) for _ in range(4)]
READS = READS * 2 + [READS[0][50:120] + READS[1][:80], "ACG", "", None, "A" * 300] + [RING * 3] * 2


def frame(spark, seqs):
    return spark.createDataFrame(list(enumerate(seqs)), "read_id long, seq string").repartition(3)


@pytest.mark.parametrize("k, parts, strict", [(5, 1, False), (11, 7, False), (11, 7, True), (21, 16, False)])
def test_nodes(spark, k, parts, strict):
    r = frame(spark, READS)
    want = contigs.nodes(kmers.extract(r.filter("seq is not null"), k), strict=strict)
    got = stretches.nodes(stretches.deal(r, "seq", k, parts, False), k, strict=strict)
    assert sorted(map(str, got.collect())) == sorted(map(str, want.collect()))


@pytest.mark.parametrize("parts", [7])
def test_contigs(spark, monkeypatch, parts):
    monkeypatch.setattr(stretches, "part_count", lambda *a: parts)
    k, r = 11, frame(spark, READS)
    f = contigs.fragments(r, "seq", k, False)
    e = contigs.fragment_edges(f)
    n = contigs.nodes(kmers.extract(r.filter("seq is not null"), k))
    plain = contigs.edges(n)
    want = sorted(map(tuple, contigs.walk_components(n, plain).collect()))
    assert len(READS[-1]) // 3 in [len(c) - k + 1 for _, c in want]
    for got in (contigs.contigs_fragments(f, e, k), contigs.walked(f, e, k), contigs.walked(f, contigs.table_edges(f, True), k)):
        assert sorted(map(tuple, got.collect())) == want
    assert sorted(map(tuple, contigs.walked(f, e, k, seeds=True).collect())) == sorted((c, len(c) - k + 1) for _, c in want)


def chain_table(places):
    """The table of a chain's fragments, one letter each, in this order; the chain runs from 0 on."""
    n = len(places)
    return pa.table({"head": pa.array([7] * n), "node": pa.array([7 + i for i in places]), "n": pa.array([1 + i % 3 for i in places]), "dst": pa.array([8 + i if i + 1 < n else None for i in places], pa.int64()), "letters": ["ACGT"[i % 4] for i in places], "first": [i == 0 for i in places]})


def test_seeds_build_a_long_chain_both_ways():
    """A chain of 10,000 fragments took a step for each two of them: some 30 s."""
    places, began = random.Random(1).sample(range(10_000), 10_000), time.process_time()
    a, z, tails, copies = contigs.from_all_seeds(chain_table(places))
    assert time.process_time() - began < 5
    assert tails.to_pylist() == ["ACGT" * 2500] and copies.tolist() == [sum(1 + i % 3 for i in places)]
    assert (places[a[0]], places[z[0]]) == (0, 9999)


def test_chains_of_the_same_letters_stay_apart():
    """Only the last letters of nodes are there: chains may differ in their heads alone."""
    t = pa.table({"node": [1, 2, 3], "n": [1, 1, 1], "dst": pa.array([None, 3, None], pa.int64()), "letters": ["A", "A", "C"], "first": [True, True, False]})
    for rows in (t, t.take([2, 0, 1])):
        for f, many in ((contigs.stepped, [1, 1]), (contigs.from_all_seeds, [1, 2])):
            a, z, tails, copies = f(rows)
            at = rows.column("node").to_pylist()
            assert sorted((at[i], at[j], x, int(c)) for i, j, x, c in zip(a, z, tails.to_pylist(), copies)) == [(1, 1, "A", 1), (2, 3, "AC", many[1])]


def test_chains_are_cut_from_batches_whole():
    heads = [1, 1, 2, 4, 4, 4, 4, 4, 9]
    batches = [pa.record_batch({"head": pa.array(heads[i:j], pa.int64())}) for i, j in ((0, 1), (1, 3), (3, 3), (3, 5), (5, 7), (7, 8), (8, 9))]
    assert [t.column("head").to_pylist() for t in contigs.whole_chains(batches)] == [[1, 1], [2], [4] * 5, [9]]


@pytest.mark.parametrize("edges, seeds", [("fragment", False), ("table", False), ("fragment", True)])
def test_many_chains_share_a_table(spark, monkeypatch, edges, seeds):
    """cg_walk, cg_generic, cg_all_seeds: each chain was a call of its own. Batches of three rows cut chains anywhere."""
    monkeypatch.setattr(stretches, "part_count", lambda *a: 7)
    k, f = 11, contigs.fragments(frame(spark, READS), "seq", 11, False)
    e = contigs.fragment_edges(f)
    want = sorted(map(tuple, contigs.contigs_fragments(f, e, k).collect()))
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 3)
    try:
        got = contigs.walked(f, e if edges == "fragment" else contigs.table_edges(f, False), k, seeds=seeds)
        assert sorted(map(tuple, got.collect())) == ([(c, len(c) - k + 1) for c in sorted(c for _, c in want)] if seeds else want)
        assert "FlatMapGroups" not in got._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_other_letters_are_an_error(spark):
    with pytest.raises(Exception, match="A, C, G and T"):
        stretches.deal(frame(spark, ["ACGTNACGT"]), "seq", 3, 2, False).collect()


NAMES = ["cg_nodes", "cg_nodes_strict", "cg_edges", "cg_heads", "cg_specialised", "cg_stats", "cg_all_seeds", "cg_contracted", "cg_generic", "cg_double", "cg_without_rings", "cg_walk", "km_two_level", "km_filter_report", "km_bloom_exact"]


@pytest.mark.parametrize("name", NAMES)
def test_little_is_moved(spark, name):
    """Bytes that the largest exchange moves: plain k-mers took over 10 bytes a letter."""
    store, gateway = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext._gateway

    def stages():
        x = store.stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList())
        return {x.apply(i).stageId(): x.apply(i).shuffleWriteBytes() for i in range(x.size())}

    before = set(stages())
    core.queries()[name](spark, SMALL).write.format("noop").mode("overwrite").save()
    letters = spark.read.parquet(f"{SMALL}/documents.parquet").agg(F.sum(F.length("text"))).first()[0]
    assert max(b for i, b in stages().items() if i not in before) < 3 * letters


def test_resize_beyond_slots(spark):
    t = KeyedTable(spark.range(100).select(F.col("id").alias("key"), "id"), slots=16).resize(None, slots=32)
    got = t.items().select(t.slot(F.col("key")).alias("s"), t.rank(F.col("key")).alias("r")).agg(F.count("*").alias("n"), F.max("s").alias("s"), F.max("r").alias("r")).first()
    assert got["n"] == 100 and got["s"] == 31 and got["r"] == 7


@pytest.mark.parametrize("name, given", [("cost_table", "events"), ("rel_sql", "part")])
def test_reads_a_table(spark, name, given):
    assert any(f.endswith(f"/{given}.parquet") for f in core.queries()[name](spark, SMALL).inputFiles())
