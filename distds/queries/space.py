"""References, arrays, collectives and atomics on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from distds.operators import atomics
from distds.operators.space import BlockArray, HostedArray, allreduce, bcast, index_of, ref_add, ref_diff, ref_of
from distds.sources.io import table

RANKS = 8


def orders_array(spark, d) -> BlockArray:
    o = table(spark, d, "orders")
    n = (o.agg(F.max("o_orderkey")).first()[0] or 0) + 1
    return BlockArray.from_df(o, "o_orderkey", "o_totalprice", n, RANKS)


def ref_arith(spark, d):
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("idx"), ref_of(F.col("o_orderkey"), 1000).alias("r"))
    o = o.withColumn("s", ref_add(F.col("r"), 1500, 1000))
    return o.select("idx", F.col("r.rank").alias("rank"), F.col("r.off").alias("off"), F.col("s.rank").alias("rank2"), F.col("s.off").alias("off2"), ref_diff(F.col("s"), F.col("r"), 1000).cast("long").alias("diff"), index_of(F.col("s"), 1000).alias("idx2"))


def lookups(spark, d):
    keys = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("idx")).distinct()
    miss = table(spark, d, "region").select((F.col("r_regionkey").cast("long") + (1 << 40)).alias("idx"))
    return keys.union(miss).withColumn("seq", F.col("idx"))


def array_get(spark, d):
    return orders_array(spark, d).get(lookups(spark, d))


def event_puts(spark, d):
    return table(spark, d, "events").select(F.col("event_id").alias("seq"), F.col("user_id").alias("idx"), F.col("value").alias("val"))


def array_put_fence(spark, d):
    return orders_array(spark, d).put(event_puts(spark, d)).fence().cells


def array_slice(spark, d):
    return orders_array(spark, d).slice(100, 900)


def hosted_array(spark, d):
    o = table(spark, d, "orders")
    a = HostedArray(o.select(F.col("o_orderkey").alias("idx"), F.col("o_totalprice").alias("val")), 1 << 40, 1, host=3)
    return a.put(event_puts(spark, d)).fence().get(lookups(spark, d))


def bulk_copy(spark, d):
    a = orders_array(spark, d)
    return a.copy_in(1000, a.copy_out(100, 250)).fence().slice(900, 1300)


def allreduce_q(spark, d):
    li = table(spark, d, "lineitem").select("l_orderkey", "l_partkey")
    k = F.col("l_partkey")
    aggs = {"total": F.sum(k), "low": F.min(k), "high": F.max(k), "all_and": F.bit_and(k), "all_or": F.bit_or(k), "all_xor": F.bit_xor(k)}
    return allreduce(li, aggs, table(spark, d, "region").select("r_regionkey"))


def bcast_join(spark, d):
    n = bcast(table(spark, d, "nation"))
    s = table(spark, d, "supplier")
    return s.join(n, s.s_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count("*").alias("suppliers"))


def amo_log(spark, d):
    e = F.col("event_id")
    mask = F.call_function("shiftleft", F.lit(1).cast("long"), (e % 60).cast("int"))
    return table(spark, d, "events").select((F.col("user_id") % 16).alias("addr"), e.alias("seq"), (e % 5 + 1).alias("delta"), mask.alias("mask"), (e % 4).alias("expect"), (F.floor(e / 4) % 4).alias("new"))


def _of(f, col):
    return lambda spark, d: f(amo_log(spark, d).select("addr", "seq", col)).select("addr", "seq", "before")


def amo_fetch_and(spark, d):
    log = amo_log(spark, d).select("addr", "seq", F.bitwise_not("mask").alias("mask"))
    return atomics.fetch_and(log, init=(1 << 60) - 1).select("addr", "seq", "before")


def amo_cas(spark, d):
    return atomics.cas_log(amo_log(spark, d), rows=2000)


def amo_cas_retry(spark, d):
    log = amo_log(spark, d).select("addr", F.floor(F.col("seq") / 100).alias("round"), "seq")
    return atomics.cas_retry(log).select("addr", "round", "seq", F.col("attempts").cast("long").alias("attempts"))


QUERIES = {
    "ref_arith": ref_arith, "array_get": array_get, "array_put_fence": array_put_fence, "array_slice": array_slice, "array_hosted": hosted_array, "bulk_copy": bulk_copy, "allreduce": allreduce_q, "bcast_join": bcast_join,
    "amo_fetch_add": _of(atomics.fetch_add, "delta"), "amo_fetch_or": _of(atomics.fetch_or, "mask"), "amo_fetch_and": amo_fetch_and, "amo_xor": _of(atomics.fetch_xor, "mask"), "amo_cas": amo_cas, "amo_cas_retry": amo_cas_retry,
}

AMO = "log AS (SELECT user_id % 16 AS addr, event_id AS seq, event_id % 5 + 1 AS delta, (1::BIGINT << (event_id % 60)::INT)::BIGINT AS mask, event_id % 4 AS expect, (event_id // 4) % 4 AS new FROM events)"
BEFORE = "OVER (PARTITION BY addr ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)"
ASKED = "asked AS (SELECT DISTINCT l_orderkey AS idx FROM lineitem UNION ALL SELECT r_regionkey::BIGINT + 1099511627776 FROM region)"
PUTS = "puts AS (SELECT user_id AS idx, arg_max(value, event_id) AS val FROM events GROUP BY 1)"
ORACLES = {
    "ref_arith": "SELECT o_orderkey AS idx, (o_orderkey // 1000)::INT AS rank, o_orderkey % 1000 AS off, ((o_orderkey + 1500) // 1000)::INT AS rank2, (o_orderkey + 1500) % 1000 AS off2, 1500::BIGINT AS diff, o_orderkey + 1500 AS idx2 FROM orders",
    "array_get": f"WITH {ASKED} SELECT idx AS seq, idx, o_totalprice AS val, o_orderkey IS NOT NULL AS found FROM asked LEFT JOIN orders ON idx = o_orderkey",
    "array_put_fence": f"WITH {PUTS} SELECT coalesce(o_orderkey, idx) AS idx, CASE WHEN idx IS NULL THEN o_totalprice ELSE val END AS val FROM orders FULL JOIN puts ON o_orderkey = idx",
    "array_slice": "SELECT o_orderkey AS idx, o_totalprice AS val FROM orders WHERE o_orderkey >= 100 AND o_orderkey < 900",
    "array_hosted": f"WITH {ASKED}, {PUTS}, cells AS (SELECT coalesce(o_orderkey, idx) AS idx, CASE WHEN idx IS NULL THEN o_totalprice ELSE val END AS val FROM orders FULL JOIN puts ON o_orderkey = idx) SELECT a.idx AS seq, a.idx, val, c.idx IS NOT NULL AS found FROM asked a LEFT JOIN cells c ON a.idx = c.idx",
    "bulk_copy": "SELECT a.o_orderkey AS idx, coalesce(b.o_totalprice, a.o_totalprice) AS val FROM orders a LEFT JOIN orders b ON a.o_orderkey BETWEEN 1000 AND 1249 AND b.o_orderkey = a.o_orderkey - 900 WHERE a.o_orderkey >= 900 AND a.o_orderkey < 1300",
    "allreduce": "SELECT r_regionkey, total, low, high, all_and, all_or, all_xor FROM region CROSS JOIN (SELECT sum(l_partkey)::BIGINT AS total, min(l_partkey) AS low, max(l_partkey) AS high, bit_and(l_partkey) AS all_and, bit_or(l_partkey) AS all_or, bit_xor(l_partkey) AS all_xor FROM lineitem)",
    "bcast_join": "SELECT n_name, count(*) AS suppliers FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY 1",
    "amo_fetch_add": f"WITH {AMO} SELECT addr, seq, coalesce(sum(delta) {BEFORE}, 0)::BIGINT AS before FROM log",
    "amo_fetch_or": f"WITH {AMO} SELECT addr, seq, coalesce(bit_or(mask) {BEFORE}, 0)::BIGINT AS before FROM log",
    "amo_fetch_and": f"WITH {AMO} SELECT addr, seq, (1152921504606846975 & coalesce(bit_and(~mask) {BEFORE}, -1))::BIGINT AS before FROM log",
    "amo_xor": f"WITH {AMO} SELECT addr, seq, coalesce(bit_xor(mask) {BEFORE}, 0)::BIGINT AS before FROM log",
    "amo_cas": f"""WITH RECURSIVE {AMO}, o AS (SELECT *, row_number() OVER (PARTITION BY addr ORDER BY seq) AS k FROM log),
        run AS (SELECT addr, k, seq, 0::BIGINT AS old, expect, new FROM o WHERE k = 1
                UNION ALL SELECT o.addr, o.k, o.seq, CASE WHEN r.old = r.expect THEN r.new ELSE r.old END, o.expect, o.new FROM run r JOIN o ON o.addr = r.addr AND o.k = r.k + 1)
        SELECT addr, seq, old, old = expect AS swapped FROM run""",
    "amo_cas_retry": f"WITH {AMO} SELECT addr, seq // 100 AS round, seq, row_number() OVER (PARTITION BY addr, seq // 100 ORDER BY seq) AS attempts FROM log",
}
