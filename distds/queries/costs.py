"""Costs, promises, engines and codecs."""

from __future__ import annotations

from pyspark.sql import functions as F

from distds.functions import codecs
from distds.plans import engines, promises
from distds.plans.promises import Promise
from distds.queries.kmers import COUNTS, K, counts
from distds.queries.queues import events_sql, log
from distds.sources.io import settle, table


def cost_table(spark, d):
    """Every plan with its costs and the events that call it; events call the plans in turn."""
    e = table(spark, d, "events").groupBy((F.col("event_id") % len(promises.PLANS)).cast("int").alias("id")).agg(F.count("*").alias("calls"))
    return promises.cost_table(spark, True).join(F.broadcast(e), "id", "left").drop("id").withColumn("calls", F.coalesce("calls", F.lit(0).cast("long")))


#: How calls of the ledger are read from the events: type of event -> (structure, method, promise).
CALLS = {"click": ("ring", "push", "push"), "view": ("table", "find", "find"), "purchase": ("table", "insert", "find+insert"), "signup": ("phase queue", "push vector", "push"), "error": ("buffer", "insert", "any")}


def cost_ledger(spark, d):
    names = spark.createDataFrame([(a, *b) for a, b in CALLS.items()], "event_type string, structure string, method string, promise string")
    e = table(spark, d, "events").select("event_type", (F.col("event_id") % 7 + 1).alias("n"))
    return promises.ledger(e.join(F.broadcast(names), "event_type"))


def promise_log(spark, d):
    e = table(spark, d, "events")
    op = F.when(F.col("event_type").isin("signup", "error"), "pop").otherwise("push")
    return e.select(F.floor(F.col("event_id") / 3).alias("phase"), op.alias("op"))


def promise_check(spark, d):
    return promises.check_promise(promise_log(spark, d), Promise.PUSH)


def promise_infer(spark, d):
    return promises.infer_promise(promise_log(spark, d))


def engine(name):
    def run(spark, d):
        rows = settle(log(spark, d, 8).select("host", "seq"))
        return engines.ENGINES[name](rows)

    return run


def codec_roundtrip(spark, d):
    """Two ints in a long and back, on composite keys of lines."""
    li = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber").distinct()
    p = li.withColumn("p", codecs.pack_pair(F.col("l_linenumber"), F.col("l_orderkey"))).withColumn("u", codecs.unpack_pair(F.col("p")))
    return p.select("l_orderkey", "l_linenumber", "p", F.col("u.a").cast("long").alias("a"), F.col("u.b").cast("long").alias("b"))


def codec_kmer_pack(spark, d):
    c = counts(spark, d).filter("n > 1").select("kmer", "n")
    f = codecs.kmer_codec(K)
    back = codecs.apply(codecs.apply(c, "kmer", f).withColumn("packed", F.col("kmer")), "kmer", f, decode=True)
    return back.groupBy(F.substring("kmer", 1, 6).alias("prefix")).agg(F.count("*").alias("kmers"), F.min("packed").alias("low"), F.max("packed").alias("high"))


def codec_heap(spark, d):
    """Texts stay in the heap and are fetched by reference."""
    heap = codecs.Heap(table(spark, d, "documents").select("doc_id", "source", "text"), "doc_id", "text", 100)
    got = heap.fetch(heap.rows, "text")
    return got.select("doc_id", F.col("ref.rank").alias("rank"), F.col("ref.off").alias("off"), "text")


QUERIES = {"cost_table": cost_table, "cost_ledger": cost_ledger, "promise_check": promise_check, "promise_infer": promise_infer, "eng_dataframe": engine("dataframe"), "eng_sql": engine("sql"), "eng_rdd": engine("rdd"), "eng_arrow": engine("arrow"), "codec_roundtrip": codec_roundtrip, "codec_kmer_pack": codec_kmer_pack, "codec_heap": codec_heap}
COSTS = "costs(structure, method, promise, a, r, w, local, barrier, each, blocking) AS (VALUES " + ", ".join(f"('{p.structure}', '{p.method}', '{p.promise}', {p.a}, {p.r}, {p.w}, {p.local}, {p.barrier}, '{p.each}', {str(p.blocking).lower()})" for p in promises.PLANS) + ")"
PHASES = "log AS (SELECT event_id // 3 AS phase, CASE WHEN event_type IN ('signup', 'error') THEN 'pop' ELSE 'push' END AS op FROM events)"
POSITIONS = f"WITH {events_sql(8)} SELECT host, seq, row_number() OVER (PARTITION BY host ORDER BY seq) - 1 AS pos FROM log"
CODE = "(" + " + ".join(f"(strpos('ACGT', substr(kmer, {i + 1}, 1)) - 1)::BIGINT * {4 ** (K - 1 - i)}" for i in range(K)) + ")"
ORACLES = {
    "cost_table": f"WITH {COSTS}, plans AS (SELECT *, row_number() OVER () - 1 AS id FROM costs), e AS (SELECT event_id % {len(promises.PLANS)} AS id, count(*) AS calls FROM events GROUP BY 1) SELECT structure, method, promise, a::INT AS a, r::INT AS r, w::INT AS w, local::INT AS local, barrier::INT AS barrier, each, blocking, coalesce(calls, 0) AS calls FROM plans LEFT JOIN e USING (id)",
    "cost_ledger": f"WITH {COSTS}, names(event_type, structure, method, promise) AS (VALUES " + ", ".join(f"('{t}', '{s}', '{m}', '{p}')" for t, (s, m, p) in CALLS.items()) + "), calls AS (SELECT structure, method, promise, event_id % 7 + 1 AS n FROM events JOIN names USING (event_type)) SELECT structure, method, promise, count(*) AS calls, " + ", ".join(f"sum({c} * CASE WHEN list_contains(string_split(each, ','), '{c}') THEN n ELSE 1 END)::BIGINT AS {c}" for c in ("a", "r", "w", "local", "barrier")) + " FROM calls JOIN costs USING (structure, method, promise) GROUP BY ALL",
    "promise_check": f"WITH {PHASES} SELECT phase, sum((op <> 'push')::BIGINT)::BIGINT AS violations FROM log GROUP BY 1",
    "promise_infer": f"WITH {PHASES} SELECT phase, CASE WHEN count(DISTINCT op) = 2 THEN 'push+pop' ELSE min(op) END AS promise FROM log GROUP BY 1",
    **{f"eng_{e}": POSITIONS for e in engines.ENGINES},
    "codec_roundtrip": "SELECT DISTINCT l_orderkey, l_linenumber, l_linenumber::BIGINT * 4294967296 + l_orderkey AS p, l_linenumber::BIGINT AS a, l_orderkey AS b FROM lineitem",
    "codec_kmer_pack": f"WITH {COUNTS} SELECT substr(kmer, 1, 6) AS prefix, count(*) AS kmers, min({CODE})::BIGINT AS low, max({CODE})::BIGINT AS high FROM c WHERE n > 1 GROUP BY 1",
    "codec_heap": "SELECT doc_id, (doc_id // 100)::INT AS rank, doc_id % 100 AS off, text FROM documents",
}
