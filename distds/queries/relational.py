"""The relational operations around the structures, on the given tables."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from distds.operators.relational import asof_join, range_join, strip_tags, top_by
from distds.sources.io import table


def money(c):
    return c.cast("decimal(18,2)")


def rel_join5(spark, d):
    t = {n: table(spark, d, n) for n in ("lineitem", "orders", "customer", "nation", "region")}
    j = t["lineitem"].join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey")).join(t["customer"], F.col("o_custkey") == F.col("c_custkey"))
    j = j.join(t["nation"], F.col("c_nationkey") == F.col("n_nationkey")).join(t["region"], F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy("r_name", "n_name").agg(F.count("*").alias("lines"), F.sum(money(F.col("l_extendedprice"))).cast("double").alias("revenue"))


def rel_semi(spark, d):
    o, li = table(spark, d, "orders"), table(spark, d, "lineitem").filter("l_quantity > 45")
    return o.join(li, o.o_orderkey == li.l_orderkey, "left_semi").select("o_orderkey")


def rel_anti(spark, d):
    o, li = table(spark, d, "orders"), table(spark, d, "lineitem")
    return o.join(li, o.o_orderkey == li.l_orderkey, "left_anti").select("o_orderkey", "o_orderstatus")


def rel_full(spark, d):
    c = table(spark, d, "customer").filter("c_acctbal > 2000").select(F.col("c_custkey").alias("k"), "c_mktsegment")
    o = table(spark, d, "orders").groupBy(F.col("o_custkey").alias("k")).agg(F.count("*").alias("orders"))
    return c.join(o, "k", "full").select("k", "c_mktsegment", "orders")


def rel_range(spark, d):
    bands = spark.createDataFrame([(i, i * 40_000.0, (i + 1) * 40_000.0) for i in range(15)], "band int, lo double, hi double")
    return range_join(table(spark, d, "orders").select("o_totalprice"), bands, "o_totalprice", "lo", "hi", 10_000.0).groupBy("band").agg(F.count("*").alias("orders"))


def rel_asof(spark, d):
    e = table(spark, d, "events")
    left = e.filter("event_type = 'purchase'").select("user_id", "event_id")
    return asof_join(left, e.filter("event_type = 'view'").select("user_id", "event_id", "value"), "user_id", "event_id", "value", "last_view")


def sums(g):
    return g.agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).cast("long").alias("quantity"))


def rel_rollup(spark, d):
    return sums(table(spark, d, "lineitem").rollup("l_returnflag", "l_linestatus"))


def rel_cube(spark, d):
    return sums(table(spark, d, "lineitem").cube("l_returnflag", "l_linestatus"))


def rel_pivot(spark, d):
    return table(spark, d, "events").groupBy((F.col("user_id") % 10).alias("u")).pivot("event_type", ["click", "error", "purchase", "signup", "view"]).count().na.fill(0)


def rel_sets(spark, d):
    a = table(spark, d, "lineitem").filter("l_returnflag = 'R'").select("l_partkey")
    b = table(spark, d, "lineitem").filter("l_quantity > 25").select("l_partkey")
    return a.intersect(b).union(a.exceptAll(b).select("l_partkey").distinct()).groupBy("l_partkey").agg(F.count("*").alias("n"))


def rel_window_rank(spark, d):
    w = Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id")
    return table(spark, d, "events").select("event_id", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(4).over(w).cast("long").alias("quarter"))


def rel_window_frame(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return table(spark, d, "events").select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("after"), F.sum(money(F.col("value"))).over(w.rowsBetween(-2, 0)).cast("double").alias("recent"), F.max("value").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("top"))


def rel_topk(spark, d):
    return top_by(table(spark, d, "orders").select("o_custkey", "o_orderkey", "o_totalprice"), "o_custkey", [F.desc("o_totalprice"), F.col("o_orderkey")], 3).withColumn("rank", F.col("rank").cast("long"))


def rel_json(spark, d):
    k = F.from_json("props", "k long")["k"]
    return table(spark, d, "events").select(k.alias("k"), "value").groupBy("k").agg(F.count("*").alias("n"), F.max("value").alias("top"))


def rel_array(spark, d):
    e = table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    dot = F.aggregate(F.zip_with("v", "v", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    return e.select("vec_id", F.size("v").cast("long").alias("dims"), F.array_max("v").alias("high"), F.size(F.filter("v", lambda x: x > 0)).cast("long").alias("positive"), F.round(dot, 6).alias("norm2"))


def rel_date(spark, d):
    o = F.col("o_orderdate")
    return table(spark, d, "orders").groupBy(F.date_trunc("month", o).alias("month")).agg(F.count("*").alias("n"), F.max(F.datediff(o, F.lit("1992-01-01"))).cast("long").alias("days"), F.min(F.unix_micros(F.col("o_orderdate").cast("timestamp"))).alias("first"))


def rel_string(spark, d):
    t = strip_tags(F.col("html"))
    host = F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)
    return table(spark, d, "pages").select("page_id", host.alias("host"), F.length(t).cast("long").alias("n"), F.upper(F.substring(host, 1, 12)).alias("head"), F.instr(t, "the").cast("long").alias("at"), F.translate(host, "aeiou", "*****").alias("masked"))


def rel_sql(spark, d):
    """The SQL surface: a table as a view, a Python table function for k-mers of each part's name, named arguments."""
    from distds.functions.udtf import register

    register(spark)
    table(spark, d, "part").createOrReplaceTempView("distds_part")
    return spark.sql("SELECT p_partkey, p, kmer FROM distds_part, LATERAL kmers(p_name, :k)", args={"k": 4})


QUERIES = {f.__name__: f for f in (rel_join5, rel_semi, rel_anti, rel_full, rel_range, rel_asof, rel_rollup, rel_cube, rel_pivot, rel_sets, rel_window_rank, rel_window_frame, rel_topk, rel_json, rel_array, rel_date, rel_string, rel_sql)}
SUMS = "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity::BIGINT)::BIGINT AS quantity FROM lineitem GROUP BY"
TEXT = "regexp_replace(html, '<[^>]*>', '', 'g')"
HOST = "regexp_extract(url, '^[a-z]+://([^/]+)', 1)"
ORACLES = {
    "rel_join5": "SELECT r_name, n_name, count(*) AS lines, sum(l_extendedprice::DECIMAL(18,2))::DOUBLE AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL",
    "rel_semi": "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45)",
    "rel_anti": "SELECT o_orderkey, o_orderstatus FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)",
    "rel_full": "SELECT coalesce(c.c_custkey, o.k) AS k, c_mktsegment, orders FROM (SELECT * FROM customer WHERE c_acctbal > 2000) c FULL JOIN (SELECT o_custkey AS k, count(*) AS orders FROM orders GROUP BY 1) o ON c.c_custkey = o.k",
    "rel_range": "SELECT floor(o_totalprice / 40000)::INT AS band, count(*) AS orders FROM orders WHERE o_totalprice >= 0 AND o_totalprice < 600000 GROUP BY 1",
    "rel_asof": "SELECT l.user_id, l.event_id, r.value AS last_view FROM (SELECT user_id, event_id FROM events WHERE event_type = 'purchase') l ASOF LEFT JOIN (SELECT user_id, event_id, value FROM events WHERE event_type = 'view') r ON l.user_id = r.user_id AND l.event_id > r.event_id",
    "rel_rollup": f"{SUMS} ROLLUP (l_returnflag, l_linestatus)", "rel_cube": f"{SUMS} CUBE (l_returnflag, l_linestatus)",
    "rel_pivot": "SELECT user_id % 10 AS u, " + ", ".join(f"count(*) FILTER (event_type = '{t}') AS {t}" for t in ("click", "error", "purchase", "signup", "view")) + " FROM events GROUP BY 1",
    "rel_sets": "WITH a AS (SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R'), b AS (SELECT l_partkey FROM lineitem WHERE l_quantity > 25), u AS (SELECT * FROM (SELECT l_partkey FROM a INTERSECT SELECT l_partkey FROM b) UNION ALL (SELECT DISTINCT l_partkey FROM (SELECT l_partkey FROM a EXCEPT ALL SELECT l_partkey FROM b))) SELECT l_partkey, count(*) AS n FROM u GROUP BY 1",
    "rel_window_rank": "SELECT event_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS quarter FROM events WINDOW w AS (PARTITION BY user_id ORDER BY value DESC, event_id)",
    "rel_window_frame": "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after, (sum(value::DECIMAL(18,2)) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW))::DOUBLE AS recent, max(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING) AS top FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)",
    "rel_topk": "SELECT o_custkey, o_orderkey, o_totalprice, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rank FROM orders QUALIFY rank <= 3",
    "rel_json": "SELECT (props::JSON->>'k')::BIGINT AS k, count(*) AS n, max(value) AS top FROM events GROUP BY 1",
    "rel_array": "SELECT vec_id, len(embedding)::BIGINT AS dims, list_max(embedding)::DOUBLE AS high, len(list_filter(embedding, lambda x: x > 0))::BIGINT AS positive, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS norm2 FROM embeddings",
    "rel_date": "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, count(*) AS n, max(date_diff('day', DATE '1992-01-01', o_orderdate::DATE)) AS days, min(epoch_us(o_orderdate)) AS first FROM orders GROUP BY 1",
    "rel_string": f"SELECT page_id, {HOST} AS host, length({TEXT}) AS n, upper(substr({HOST}, 1, 12)) AS head, strpos({TEXT}, 'the') AS at, translate({HOST}, 'aeiou', '*****') AS masked FROM pages",
    "rel_sql": "SELECT p_partkey, p, substr(p_name, p, 4) AS kmer FROM (SELECT p_partkey, p_name, unnest(range(1, length(p_name) - 2))::INT AS p FROM part WHERE length(p_name) >= 4)",
}
