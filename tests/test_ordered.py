"""One filter over k-mers in the order of reads: against its SQL, and what it moves and leaves on disk."""

import hashlib
import os
import random

import numpy as np
import pytest
from conftest import SMALL
from pyspark.sql import functions as F

from distds import queries as core
from distds.functions.hashing import h60_kmers
from distds.plans import kmers, ordered
from distds.sources.io import shared_path

SEEDED = random.Random(7)
WORDS = ["".join(SEEDED.choice("abcdefghij") for _ in range(SEEDED.randint(3, 9))) for _ in range(300)]
TEXTS = [" ".join(SEEDED.choice(WORDS) for _ in range(SEEDED.randint(1, 900))) for _ in range(60)]
TEXTS += [*TEXTS[:5], None, "", "short", "B" * 3000, "aB" * 50, "é, ÀB1 " * 30, " ".join(WORDS) * 12]


def oracle(duck, docs):
    duck.register("given", docs.toPandas())
    duck.sql("create or replace temp view documents as select * from given")
    try:
        return duck.sql(core.oracle_sql()["km_bloom"]).arrow().read_all()
    finally:
        duck.sql("drop view temp.documents")


def told(rows):
    return sorted(tuple(r[c] for c in ("prefix", "kmers", "fp", "hits", "reported", "occ")) for r in rows)


@pytest.mark.parametrize("ids, cap, rounds, parts", [("descending", 1 << 18, 1, 8), ("descending", 512, 3, 5), ("one null", 300, 2, 1), ("copies", 400, 3, 7)])
def test_as_its_sql(spark, duck, monkeypatch, ids, cap, rounds, parts):
    """Rows of any length, reads longer than a row, any number of rounds; the read without an id comes last; copies share an id."""
    monkeypatch.setattr(ordered, "CAP", cap)
    rows = [(1000 - 7 * i, t) for i, t in enumerate(TEXTS)]
    if ids == "one null":
        rows[3] = None, rows[3][1]
    if ids == "copies":
        rows += rows[:40]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    got = ordered.report(docs, "doc_id", "text", 21, 4, rounds, parts)
    assert told(got.collect()) == told(oracle(duck, docs).to_pylist())


def test_reads_that_share_an_id(monkeypatch):
    """k-mers of such reads are in order of their places."""
    monkeypatch.setattr(ordered, "CAP", 90)
    reads = [np.array([SEEDED.randrange(4) for _ in range(n)], np.uint8) for n in (200, 57, 21)]
    held = []
    for x in reads:
        four = np.concatenate([x, np.zeros(-len(x) % 4, np.uint8)]).reshape(-1, 4)
        held.append((len(x), (four[:, 0] << 6 | four[:, 1] << 4 | four[:, 2] << 2 | four[:, 3]).tobytes()))
    got = []
    for s in ordered.slices(held, 21):
        got += ordered.ordered(np.array([n for n, _ in s]), np.zeros(len(s), np.int64), b"".join(x for _, x in s), 21).tolist()
    mers = [[int("".join(map(str, x[p : p + 21])), 4) for p in range(len(x) - 20)] for x in reads]
    assert got == [m[p] for p in range(180) for m in mers if p < len(m)]


def test_many_sightings_in_a_row(spark, duck):
    """Beyond what a byte can tell."""
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(["A" * (20 + n) for n in (253, 254, 255, 256, 900)] + ["AC" * 70])], "doc_id long, text string")
    assert told(ordered.report(docs, "doc_id", "text", 21, 4, 2, 3).collect()) == told(oracle(duck, docs).to_pylist())


def test_no_reads(spark):
    docs = spark.createDataFrame([(1, None), (2, "too short")], "doc_id long, text string")
    assert ordered.report(docs, "doc_id", "text", 21, 4).collect() == []


def test_distinct_by_either_sort():
    mers = np.array([SEEDED.randrange(50) for _ in range(500)], np.uint64)
    for a, b in zip(ordered.distinct(mers, 21), ordered.distinct(mers, 29)):
        assert a.tolist() == b.tolist() and ordered.distinct(mers, 31)[1].tolist() == ordered.distinct(mers, 21)[1].tolist()


@pytest.mark.parametrize("k, seed", [(1, 0), (2, 10), (21, 1), (21, 2), (29, 3)])
def test_hash(k, seed):
    mers = [SEEDED.randrange(4**k) for _ in range(200)]
    text = ["".join("ACGT"[m >> 2 * (k - 1 - j) & 3] for j in range(k)) for m in mers]
    assert h60_kmers(np.array(mers, np.uint64), k, seed).tolist() == [int(hashlib.md5(f"{seed}#{t}".encode()).hexdigest()[:15], 16) for t in text]


def test_little_is_moved(spark):
    """All exchanges of km_bloom together, and what it leaves in the shared folder: plain k-mers took over 10 bytes a letter in one."""
    store, gateway = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext._gateway

    def stages():
        x = store.stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList())
        return {x.apply(i).stageId(): x.apply(i).shuffleWriteBytes() for i in range(x.size())}

    root = os.path.dirname(shared_path(spark)).removeprefix("file:")
    before, there = set(stages()), set(os.listdir(root) if os.path.isdir(root) else [])
    core.queries()["km_bloom"](spark, SMALL).write.format("noop").mode("overwrite").save()
    letters = spark.read.parquet(f"{SMALL}/documents.parquet").agg(F.sum(F.length("text"))).first()[0]
    assert sum(b for i, b in stages().items() if i not in before) < 8 * letters
    left = [os.path.join(d, f) for x in set(os.listdir(root)) - there for d, _, names in os.walk(os.path.join(root, x)) for f in names]
    assert sum(map(os.path.getsize, left)) < 100_000


def test_rounds_share_the_sightings(spark):
    """No round sends much more than its share."""
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    table = ordered.rows(ordered.packed(docs, "doc_id", "text", 21), 21, 8).cache()
    total = table.agg(F.sum("n")).first()[0]
    assert total == kmers.sightings(kmers.reads_from_text(docs, "doc_id", "text"), 21)
    n = [ordered.sent(table, 21, kmers.blocks_for(total), 4, t, 3).agg(F.sum(F.length("packet"))).first()[0] for t in range(3)]
    assert max(n) < 1.1 * sum(n) / 3 and sum(n) < 6 * total
