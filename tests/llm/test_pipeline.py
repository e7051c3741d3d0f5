"""The pipeline's stages on the smallest tables, each against its own brute force."""

import collections

import pytest
from conftest import SMALL
from pyspark.sql import functions as F

import corpus_pipeline as cp
from distds.llm import queries as llm
from distds.llm.scratch import Scratch


@pytest.fixture(scope="module")
def stages(spark):
    scratch, docs = Scratch(spark), spark.read.parquet(f"{SMALL}/documents.parquet")
    out = [docs]
    for _, f in cp.STAGES:
        out.append(scratch.stash(f(spark, out[-1], SMALL)))
    return out


def text_of(df):
    return collections.Counter((r["doc_id"], r["text"]) for r in df.collect())


def test_columns_stay(stages):
    assert all(d.columns == list(cp.COLUMNS) for d in stages[:-1]) and len(cp.STAGES) == 5


def test_quality_drops_bad_and_keeps_good(spark, stages):
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{SMALL}/labels.parquet").collect()}
    kept = {r["doc_id"] for r in stages[1].collect()}
    good, bad = ([i for i, q in labels.items() if q == y] for y in (1, 0))
    assert sum(i in kept for i in good) / len(good) > 0.97 and sum(i in kept for i in bad) / len(bad) < 0.3


def test_line_dedup_by_source(stages):
    """Copies count once; texts made of frequent lines by half or more have one vote for a line together."""
    before = stages[1].collect()
    texts = collections.defaultdict(dict)
    for r in before:
        texts[r["source"]][r["text"]] = {x.strip(" ") for x in r["text"].split("\n")} - {""}
    boiler = {}
    for s, ts in texts.items():
        def often(n):
            return {x for x, k in n.items() if k - 1 > 0.1 * (len(ts) - 1)}

        first = often(collections.Counter(x for lines in ts.values() for x in lines))
        votes, heavy = collections.Counter(), set()
        for lines in ts.values():
            hit = lines & first
            if 2 * sum(map(len, hit)) >= sum(map(len, lines)):
                heavy |= hit
            else:
                votes.update(hit)
        votes.update(heavy)
        boiler[s] = often(votes)
    want = collections.Counter()
    for r in before:
        lines = r["text"].split("\n")
        kept = [x for x in lines if x.strip(" ") not in boiler[r["source"]]]
        want[r["doc_id"], "\n".join(kept if any(x.strip(" ") for x in kept) else lines)] += 1
    assert text_of(stages[2]) == want


def test_one_of_each_near_group_stays(stages):
    rows = [(r["doc_id"], r["text"]) for r in stages[2].collect()]
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for w in (t.lower().encode().split() for _, t in rows)]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            c = len(sets[a] & sets[b])
            if 100 * c >= 80 * (len(sets[a]) + len(sets[b]) - c):
                root[find(a)] = find(b)
    low = {}
    for i, (d, _) in enumerate(rows):
        low[find(i)] = min(d, low.get(find(i), d))
    assert {r["doc_id"] for r in stages[3].collect()} == set(low.values()) and stages[3].count() == len(low)


def test_mix_and_packing(spark, stages):
    mixed = text_of(stages[4])
    assert set(mixed.values()) <= {1, 2} and set(mixed) <= set(text_of(stages[3]))
    total = sum(len(t.encode().split()) * n for (_, t), n in text_of(stages[3]).items())
    assert sum(len(t.encode().split()) * n for (_, t), n in mixed.items()) == pytest.approx(1.5 * total, rel=0.3)
    assert stages[5].agg(F.sum("length")).first()[0] == sum(len(t.encode().split()) * n for (_, t), n in mixed.items())


def test_empty_documents(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").limit(0)
    for _, f in cp.STAGES:
        assert f(spark, docs, SMALL).count() == 0


def test_repeated_rows_leave_one(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").limit(5)
    assert cp.without_near_copies(spark, docs.union(docs), SMALL).count() == cp.without_near_copies(spark, docs, SMALL).count()


def test_near_groups_with_null_and_repeated_ids(spark):
    """One text of each group stays where all ids are null, where two texts share the smallest id, and where some are null."""
    base = [" ".join(f"{g}{j}" for j in range(60)) for g in "abc"]
    rows = [(None, f"{base[0]} end{i}") for i in range(4)] + [(7, f"{base[1]} end{i}") for i in range(3)] + [(9, f"{base[1]} more")]
    rows += [(None, f"{base[2]} end"), (5, f"{base[2]} more"), (6, f"{base[2]} most"), (None, "no copy of it here"), (7, "no copy of this one either")]
    docs = spark.createDataFrame([(i, t, "en", "s", 1) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    for d in (docs, docs.union(docs)):
        got = cp.without_near_copies(spark, d, SMALL).collect()
        assert collections.Counter((r["doc_id"], r["text"][:3]) for r in got) == collections.Counter([(None, "a0 "), (7, "b0 "), (5, "c0 "), (None, "no "), (7, "no ")])


def prose(i, lines=6):
    return "\n".join(f"line {j} of text {i} tells story {i * 31 + j} in words of its own" for j in range(lines))


def test_line_dedup_leaves_one_of_each_group_of_copies(spark):
    """Hot copies and near copies, and pairs in sources of 10 to 19 documents, reach the near-duplicate stage whole."""
    rows = [(i, prose(i), "en", "hot", 1) for i in range(40)]
    rows += [(100 + i, prose(100), "en", "hot", 1) for i in range(20)]
    rows += [(200 + i, prose(200) + f"\nlast line {i}", "en", "hot", 1) for i in range(10)]
    rows += [(300 + i, prose(max(i, 1) + 300), "en", "ten", 1) for i in range(10)]
    rows += [(400 + i, prose(max(i, 1) + 400), "en", "many", 1) for i in range(19)]
    rows += [(500 + i, prose(501 if i < 2 else i + 500) + f"\nend {i}", "en", "near", 1) for i in range(10)]
    kept = cp.without_boilerplate(spark, spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long"), SMALL)
    assert text_of(kept) == collections.Counter((r[0], r[1]) for r in rows)


def test_line_dedup_still_drops_boilerplate(spark):
    """A line of many different texts goes from all, copies of one text too; a document of nothing else stays."""
    rows = [(i, prose(i) + "\nShare this page", "en", "s", 1) for i in range(20)] + [(50 + i, prose(50) + "\nShare this page", "en", "s", 1) for i in range(9)]
    rows += [(90, "Share this page", "en", "s", 1)]
    kept = cp.without_boilerplate(spark, spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long"), SMALL)
    assert text_of(kept) == collections.Counter((r[0], r[1].replace("\nShare this page", "")) for r in rows)


@pytest.mark.parametrize("name", sorted(llm.oracle_sql()))
def test_oracle(spark, duck, name):
    from conftest import same

    same(llm.queries()[name](spark, SMALL), duck.sql(llm.oracle_sql()[name]))
