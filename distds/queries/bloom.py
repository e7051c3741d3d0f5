"""Bloom filters over the event log and over part keys."""

from __future__ import annotations

from pyspark.sql import functions as F

from distds.functions.hashing import h60, h60_sql
from distds.operators.bloom import BlockedBloom, ScatterBloom, fpr, race_claims
from distds.sources.io import table

BITS, BLOCKS, K = 4096, 64, 4


def values(spark, d):
    """seq, x: user ids in the order of events."""
    return table(spark, d, "events").select(F.col("event_id").alias("seq"), F.col("user_id").alias("x"))


def parts(spark, d):
    """Inserted keys: all suppliers. Asked are all parts, most of which are absent."""
    return table(spark, d, "supplier").select(F.col("s_suppkey").alias("x"))


def asks(spark, d):
    return table(spark, d, "part").select(F.col("p_partkey").alias("seq"), F.col("p_partkey").alias("x"))


def sb_insert(spark, d):
    return ScatterBloom(BITS, K).insert(values(spark, d))


def sb_find(spark, d):
    f = ScatterBloom(BITS, K)
    return f.find(asks(spark, d), f.build(parts(spark, d)))


def sb_race(spark, d):
    """Pairs of events of one user insert at once: bit j of both, then bit j + 1. Each may find some bit unset."""
    v = values(spark, d).withColumn("x", F.floor(F.col("seq") / 2))
    bits = F.array(*[F.pmod(h60(F.col("x"), 10 + j), F.lit(1 << 24)) for j in range(K)])
    step = v.select("seq", "x", F.posexplode(bits).alias("j", "bit"))
    turn = (F.col("j") + F.col("seq")) % 2
    return race_claims(step.select((F.col("x") * 64 + F.col("j") * 2 + turn).alias("step"), F.col("seq").alias("op"), "x", "bit"))


def bb_insert(spark, d):
    return BlockedBloom(BLOCKS, K).insert(values(spark, d))


def some_null(spark, d):
    """The same log with every seventh value missing."""
    return values(spark, d).withColumn("x", F.when(F.col("seq") % 7 != 0, F.col("x")))


def sb_insert_nulls(spark, d):
    return ScatterBloom(BITS, K).insert(some_null(spark, d))


def bb_insert_nulls(spark, d):
    return BlockedBloom(BLOCKS, K).insert(some_null(spark, d))


def bb_find(spark, d):
    f = BlockedBloom(512, K)
    return f.find(asks(spark, d), f.build(parts(spark, d)))


def bb_build(spark, d):
    return BlockedBloom(512, K).build(parts(spark, d)).select("block", F.bit_count("mask").cast("int").alias("bits"))


def bb_merge(spark, d):
    f, p = BlockedBloom(512, K), parts(spark, d)
    return f.merge(f.build(p.filter("x % 2 = 0")), f.build(p.filter("x % 2 = 1"))).select("block", F.bit_count("mask").cast("int").alias("bits"))


def bb_wide(spark, d):
    """Blocks of four words: no false negatives among the keys that were inserted."""
    f = BlockedBloom(128, K).wide(4)
    return f.find(asks(spark, d), f.build(parts(spark, d)))


def bb_fpr(spark, d):
    """Measured and expected rates of false positives for keys that were never inserted."""
    keys = table(spark, d, "orders").select(F.col("o_orderkey").alias("x"))
    n = keys.count()
    rows = None
    for load in (4, 8):
        f = BlockedBloom(max(1, n // load), K)
        absent = spark.range(1 << 41, (1 << 41) + 20_000).select(F.col("id").alias("seq"), F.col("id").alias("x"))
        got = f.find(absent, f.build(keys)).agg(F.lit(load).alias("load"), F.round(F.avg(F.col("present").cast("double")), 6).alias("measured"), F.lit(round(fpr(n, f.blocks, K), 6)).alias("expected"))
        rows = got if rows is None else rows.union(got)
    return rows


QUERIES = {f.__name__: f for f in (sb_insert, sb_find, sb_race, bb_insert, bb_find, bb_build, bb_merge, bb_wide, bb_fpr, sb_insert_nulls, bb_insert_nulls)}


def places_sql(expr, bits):
    return f"list_distinct([{', '.join(f'{h60_sql(expr, 10 + j)} % {bits}' for j in range(K))}])"


def mask_sql(expr):
    h = h60_sql(expr, 2)
    return "(" + " | ".join(f"(1::UBIGINT << ((({h}) >> {6 * j}) & 63)::UBIGINT)" for j in range(K)) + ")"


KEYS = "SELECT s_suppkey AS x FROM supplier"
BUILD = f"SELECT {h60_sql('x', 1)} % 512 AS block, bit_or({mask_sql('x')}) AS mask FROM ({KEYS}) GROUP BY 1"
ORACLES = {
    "sb_insert": f"WITH b AS (SELECT event_id AS seq, unnest({places_sql('user_id', BITS)}) AS bit FROM events), f AS (SELECT bit, min(seq) AS first FROM b GROUP BY 1) SELECT seq, bool_and(first < seq) AS present FROM b JOIN f USING (bit) GROUP BY 1",
    "sb_race": f"""WITH s AS (SELECT x, op, b.bit AS bit, x * 64 + b.j * 2 + (b.j + op) % 2 AS step FROM (SELECT event_id AS op, event_id // 2 AS x, unnest([{', '.join(f"{{'j': {j}, 'bit': {h60_sql('event_id // 2', 10 + j)} % {1 << 24}}}" for j in range(K))}]) AS b FROM events)),
        u AS (SELECT x, op, count(*) OVER (PARTITION BY bit ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) = 0 AS unset FROM s)
        SELECT x, sum(c::BIGINT)::BIGINT AS claims FROM (SELECT x, op, bool_or(unset) AS c FROM u GROUP BY ALL) GROUP BY 1""",
    "sb_find": f"WITH s AS (SELECT DISTINCT unnest({places_sql('x', BITS)}) AS bit FROM ({KEYS})), a AS (SELECT p_partkey AS seq, unnest({places_sql('p_partkey', BITS)}) AS bit FROM part) SELECT seq, bool_and(s.bit IS NOT NULL) AS present FROM a LEFT JOIN s USING (bit) GROUP BY 1",
    "bb_insert": f"""WITH m AS (SELECT event_id AS seq, {h60_sql('user_id', 1)} % {BLOCKS} AS block, {mask_sql('user_id')} AS mask FROM events),
        p AS (SELECT seq, mask, coalesce(bit_or(mask) OVER (PARTITION BY block ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0::UBIGINT) AS prev FROM m) SELECT seq, (prev & mask) = mask AS present FROM p""",
    "bb_find": f"WITH s AS ({BUILD}), a AS (SELECT p_partkey AS seq, {h60_sql('p_partkey', 1)} % 512 AS block, {mask_sql('p_partkey')} AS m FROM part) SELECT seq, (coalesce(mask, 0::UBIGINT) & m) = m AS present FROM a LEFT JOIN s USING (block)",
    "bb_build": f"SELECT block, bit_count(mask)::INT AS bits FROM ({BUILD})",
    "bb_merge": f"SELECT block, bit_count(mask)::INT AS bits FROM ({BUILD})",
}
LANES = ", ".join(f"{{'word': {h60_sql('x', 20 + j)} % 4, 'bit': ({h60_sql('x', 2)} >> {6 * j}) & 63}}" for j in range(K))
WIDE = f"SELECT DISTINCT block, l.word AS word, l.bit AS bit FROM (SELECT {h60_sql('x', 1)} % 128 AS block, unnest([{LANES}]) AS l FROM"
ORACLES["bb_wide"] = f"""WITH s AS ({WIDE} ({KEYS}))), a AS (SELECT seq, {h60_sql('x', 1)} % 128 AS block, unnest([{LANES}]) AS l FROM (SELECT p_partkey AS seq, p_partkey AS x FROM part))
    SELECT seq, bool_and(s.bit IS NOT NULL) AS present FROM a LEFT JOIN s ON s.block = a.block AND s.word = a.l.word AND s.bit = a.l.bit GROUP BY 1"""
FIRST = "SELECT seq, bool_and(first < seq) AS present FROM b JOIN f USING (bit) GROUP BY 1"
ORACLES["sb_insert_nulls"] = f"WITH b AS (SELECT event_id AS seq, unnest({places_sql('user_id', BITS)}) AS bit FROM events WHERE event_id % 7 <> 0), f AS (SELECT bit, min(seq) AS first FROM b GROUP BY 1) {FIRST} UNION ALL SELECT event_id, false FROM events WHERE event_id % 7 = 0"
ORACLES["bb_insert_nulls"] = ORACLES["bb_insert"].replace("FROM events)", "FROM events WHERE event_id % 7 <> 0)") + " UNION ALL SELECT event_id, false FROM events WHERE event_id % 7 = 0"
#: The expected rate sums over Poisson loads of a block, as ``fpr`` does.
ORACLES["bb_fpr"] = f"""WITH b AS (SELECT load, n, greatest(1, n // load) AS blocks FROM (SELECT count(*) AS n FROM orders) CROSS JOIN (SELECT unnest([4, 8])::INT AS load)),
    s AS (SELECT load, {h60_sql('o_orderkey', 1)} % blocks AS block, bit_or({mask_sql('o_orderkey')}) AS mask FROM orders CROSS JOIN b GROUP BY ALL),
    a AS (SELECT load, {h60_sql('x', 1)} % blocks AS block, {mask_sql('x')} AS m FROM (SELECT unnest(range(1::BIGINT << 41, (1::BIGINT << 41) + 20000)) AS x) CROSS JOIN b),
    got AS (SELECT a.load, avg(((coalesce(mask, 0::UBIGINT) & m) = m)::INT::DOUBLE) AS measured FROM a LEFT JOIN s ON s.load = a.load AND s.block = a.block GROUP BY 1),
    p AS (SELECT load, n::DOUBLE / blocks AS x, unnest(range(1, floor(n::DOUBLE / blocks + 12 * sqrt(n::DOUBLE / blocks) + 40)::BIGINT)) AS i FROM b),
    want AS (SELECT load, sum(exp(i * ln(x) - x - lgamma(i + 1)) * pow(1 - pow(1 - 1 / 64.0::DOUBLE, {K} * i), {K})) AS expected FROM p GROUP BY 1)
    SELECT load, round(measured, 6) AS measured, round(expected, 6) AS expected FROM got JOIN want USING (load)"""
