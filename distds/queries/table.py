"""The hash table, its buffered writer, and its layout."""

from __future__ import annotations

from pyspark.sql import functions as F

from distds.functions.hashing import h60_sql
from distds.operators.keyed_table import KeyedTable, StagedWriter, decode_flag, layout, layout_global, probe_stats, replay_flag
from distds.plans.micro import insert_buffered, insert_direct
from distds.plans.promises import Promise
from distds.queries.space import ASKED, lookups
from distds.sources.io import settle, table

KEYS = 100  # capacity of the bounded table in kt_insert_full


def event_inserts(spark, d):
    return table(spark, d, "events").select(F.col("event_id").alias("seq"), F.col("user_id").alias("key"), F.col("value").alias("val"))


def empty(spark, **kw):
    return KeyedTable.create(spark, "long", "double", **kw)


def orders_table(spark, d):
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("key"), F.col("o_totalprice").alias("val"))
    return KeyedTable(o)


def kt_insert_replace(spark, d):
    return empty(spark).insert(event_inserts(spark, d))[0].items()


def kt_insert_keep(spark, d):
    return empty(spark).insert(event_inserts(spark, d), on_dup="keep")[0].items()


def line_inserts(spark, d):
    return table(spark, d, "lineitem").select(F.lit(0).cast("long").alias("seq"), F.col("l_orderkey").alias("key"), F.col("l_quantity").cast("long").alias("val"))


def kt_insert_merge(spark, d):
    return KeyedTable.create(spark, "long", "long").insert(line_inserts(spark, d), on_dup="merge", merge=F.sum)[0].items()


def kt_insert_local(spark, d):
    t = empty(spark)
    return t.insert(t.place_local(event_inserts(spark, d)), promise=Promise.LOCAL)[0].items()


def viewed(spark, d):
    """A table that holds the last viewed value of each user."""
    return KeyedTable(settle(empty(spark).insert(event_inserts(spark, d).join(views(spark, d), "seq", "left_semi"))[0].state))


def views(spark, d):
    return table(spark, d, "events").filter("event_type = 'view'").select(F.col("event_id").alias("seq"))


def kt_insert_local_filled(spark, d):
    """Everything but views is inserted locally into the table of views; the last wins."""
    t = viewed(spark, d)
    return t.insert(t.place_local(event_inserts(spark, d).join(views(spark, d), "seq", "left_anti")), promise=Promise.LOCAL)[0].items()


def kt_insert_local_keep(spark, d):
    t = viewed(spark, d)
    return t.insert(t.place_local(event_inserts(spark, d).join(views(spark, d), "seq", "left_anti")), promise=Promise.LOCAL, on_dup="keep")[0].items()


def sw_flush_local(spark, d):
    """Half of the lines through one writer, half through another whose owners insert locally into the table of the first."""
    rows = line_inserts(spark, d)
    first = StagedWriter(KeyedTable.create(spark, "long", "long"), on_dup="merge", merge=F.sum).insert(rows.filter("val % 2 = 0")).flush()
    w = StagedWriter(KeyedTable(settle(first.state)), on_dup="merge", merge=F.sum, local=True)
    return w.insert(rows.filter("val % 2 = 1")).flush().items()


def kt_insert_full(spark, d):
    return empty(spark, capacity=KEYS).insert(event_inserts(spark, d))[1].select("seq", "ok")


def find_log(spark, d):
    e = table(spark, d, "events")
    return e.select(F.col("event_id").alias("seq"), F.col("user_id").alias("key"), F.when(F.col("event_type") == "view", "find").otherwise("insert").alias("op"), F.col("value").alias("val"))


def kt_find_atomic(spark, d):
    return empty(spark).run_log(find_log(spark, d))


def kt_find_hot(spark, d):
    """The same log, cut so that a hot key is split."""
    return empty(spark).run_log(find_log(spark, d), hot=True)


def kt_find_only(spark, d):
    return orders_table(spark, d).find(lookups(spark, d).withColumnRenamed("idx", "key"), Promise.FIND)


def kt_delete(spark, d):
    gone = table(spark, d, "lineitem").filter("l_returnflag = 'R'").select(F.col("l_orderkey").alias("key"))
    return orders_table(spark, d).delete(gone).items()


def kt_contains(spark, d):
    return orders_table(spark, d).contains(lookups(spark, d).select(F.col("idx").alias("key")))


def kt_resize(spark, d):
    t = KeyedTable(orders_table(spark, d).state, slots=1 << 18).resize(None, slots=1 << 19)  # orders may outnumber the slots
    return t.items().select("key", t.slot(F.col("key")).alias("slot"), t.rank(F.col("key")).alias("rank"))


def flag_words(spark, d):
    e = F.col("event_id")
    return table(spark, d, "events").select((e % 64).alias("bucket"), e.alias("step"), F.pmod(e * 2654435761, F.lit(1 << 32)).alias("word"))


def kt_flag_decode(spark, d):
    f = flag_words(spark, d).withColumn("f", decode_flag(F.col("word")))
    return f.select("step", F.col("f.status").alias("status"), F.col("f.readers").alias("readers"))


def kt_flag_replay(spark, d):
    return replay_flag(flag_words(spark, d)).groupBy("state", "legal").agg(F.count("*").alias("n"))


def placed(spark, d):
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("key"), F.col("o_orderkey").alias("seq"))
    return layout(o, 2 * o.count())


def kt_layout(spark, d):
    return placed(spark, d)


def kt_probe_stats(spark, d):
    return probe_stats(placed(spark, d), 2 * table(spark, d, "orders").count())


def kt_layout_global(spark, d):
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("key"), F.col("o_orderkey").alias("seq"))
    return layout_global(o, 4 * o.count()).select("key", "slot", "probes", "ok")


def micro_direct(spark, d):
    return insert_direct(line_inserts(spark, d), 4)


def micro_buffered(spark, d):
    return insert_buffered(line_inserts(spark, d), 4)


def staged(spark, d):
    return StagedWriter(KeyedTable.create(spark, "long", "long"), message_size=64, on_dup="merge", merge=F.sum).insert(line_inserts(spark, d).filter("key % 2 = 0")).insert(line_inserts(spark, d).filter("key % 2 = 1"))


def sw_flush(spark, d):
    return staged(spark, d).flush().items()


def sw_ordered(spark, d):
    return StagedWriter(empty(spark)).insert(event_inserts(spark, d)).flush().items()


def sw_messages(spark, d):
    w = StagedWriter(KeyedTable.create(spark, "long", "long"), message_size=64)
    return w.insert(line_inserts(spark, d)).messages(F.pmod(F.col("key"), F.lit(16)))


def sw_equals_direct(spark, d):
    a, b = sw_flush(spark, d), kt_insert_merge(spark, d)
    return a.exceptAll(b).union(b.exceptAll(a)).agg(F.count("*").alias("differences"))


QUERIES = {f.__name__: f for f in (kt_insert_replace, kt_insert_keep, kt_insert_merge, kt_insert_local, kt_insert_local_filled, kt_insert_local_keep, sw_flush_local, kt_insert_full, kt_find_atomic, kt_find_hot, kt_find_only, kt_delete, kt_contains, kt_resize, kt_flag_decode, kt_flag_replay, kt_layout, kt_layout_global, kt_probe_stats, micro_direct, micro_buffered, sw_flush, sw_ordered, sw_messages, sw_equals_direct)}
LAST = "SELECT user_id AS key, arg_max(value, event_id) AS val FROM events GROUP BY 1"
SUMS = "SELECT l_orderkey AS key, sum(l_quantity::BIGINT)::BIGINT AS val FROM lineitem GROUP BY 1"
WORD = "words AS (SELECT event_id % 64 AS bucket, event_id AS step, (event_id::HUGEINT * 2654435761 % 4294967296)::BIGINT AS word FROM events)"
FLAG = "list_extract(['free', 'reserved', 'ready', 'invalid'], (word & 3)::INT + 1)"


def placement_sql(factor: int, block: int | None) -> str:
    """Lock-step placement: every round all keys without a slot ask for their next one, and the first key of each free slot wins."""
    wide = "size" if block is None else f"least({block}, size)"
    return f"""WITH RECURSIVE t AS (SELECT (1::BIGINT << ceil(log2({factor} * count(*)))::INT) AS size FROM orders), k AS MATERIALIZED (SELECT o_orderkey AS key, {h60_sql('o_orderkey')} % size AS h, {wide} AS b FROM orders CROSS JOIN t),
        s AS (SELECT key, h, b, 0::BIGINT AS i, NULL::BIGINT AS slot, 0::BIGINT AS probes FROM k UNION ALL
            SELECT key, h, b, i + 1, CASE WHEN slot IS NULL AND held IS NULL AND r = 1 THEN want ELSE slot END, CASE WHEN slot IS NULL THEN i + 1 ELSE probes END
            FROM (SELECT w.*, p.slot AS held, row_number() OVER (PARTITION BY w.want, w.slot IS NULL ORDER BY w.key) AS r FROM (SELECT *, h // b * b + (h % b + i * (i + 1) // 2) % b AS want FROM s) w LEFT JOIN (SELECT slot FROM s WHERE slot IS NOT NULL) p ON p.slot = w.want)
            WHERE EXISTS (SELECT 1 FROM s WHERE slot IS NULL)),
        placed AS (SELECT * FROM s WHERE i = (SELECT max(i) FROM s))"""


ORACLES = {
    "kt_layout": f"{placement_sql(2, 1 << 15)} SELECT key, (h // b)::INT AS block, slot, probes, true AS ok FROM placed",
    "kt_layout_global": f"{placement_sql(4, None)} SELECT key, slot, probes, true AS ok FROM placed",
    "kt_probe_stats": f"{placement_sql(2, 1 << 15)} SELECT count(*) / (SELECT size FROM t) AS load, avg(probes) AS avg_probes, max(probes) AS max_probes FROM placed",
    "kt_insert_local_filled": "SELECT user_id AS key, arg_max(value, (event_type <> 'view')::BIGINT * 1000000000000 + event_id) AS val FROM events GROUP BY 1",
    "kt_insert_local_keep": "SELECT user_id AS key, arg_min(value, CASE WHEN event_type = 'view' THEN -event_id ELSE event_id END) AS val FROM events GROUP BY 1",
    "sw_flush_local": SUMS,
    "kt_insert_replace": LAST, "kt_insert_local": LAST, "sw_ordered": LAST,
    "kt_insert_keep": "SELECT user_id AS key, arg_min(value, event_id) AS val FROM events GROUP BY 1",
    "kt_insert_merge": SUMS, "micro_direct": SUMS, "micro_buffered": SUMS,
    "sw_flush": SUMS,
    "kt_insert_full": f"WITH f AS (SELECT user_id, row_number() OVER (ORDER BY min(event_id)) AS k FROM events GROUP BY 1) SELECT event_id AS seq, k <= {KEYS} AS ok FROM events JOIN f USING (user_id)",
    **dict.fromkeys(("kt_find_atomic", "kt_find_hot"), """WITH o AS (SELECT event_id AS seq, user_id AS key, event_type, last_value(CASE WHEN event_type <> 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prev FROM events)
        SELECT o.seq, o.key, e.value AS val, o.prev IS NOT NULL AS found FROM o LEFT JOIN events e ON e.event_id = o.prev WHERE o.event_type = 'view'"""),
    "kt_find_only": f"WITH {ASKED} SELECT idx AS seq, idx AS key, o_totalprice AS val, o_orderkey IS NOT NULL AS found FROM asked LEFT JOIN orders ON idx = o_orderkey",
    "kt_delete": "SELECT o_orderkey AS key, o_totalprice AS val FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'R')",
    "kt_contains": f"WITH {ASKED} SELECT idx AS key FROM asked WHERE idx IN (SELECT o_orderkey FROM orders)",
    "kt_resize": f"SELECT o_orderkey AS key, {h60_sql('o_orderkey')} % 524288 AS slot, (({h60_sql('o_orderkey')} % 524288) // 65536)::INT AS rank FROM orders",
    "kt_flag_decode": f"WITH {WORD} SELECT step, {FLAG} AS status, bit_count((word >> 2) & 1073741823)::INT AS readers FROM words",
    "kt_flag_replay": f"""WITH {WORD}, s AS (SELECT bucket, step, {FLAG} AS state, bit_count((word >> 2) & 1073741823)::INT AS readers FROM words),
        p AS (SELECT *, coalesce(lag(state) OVER w, 'free') AS before, coalesce(lag(readers) OVER w, 0) AS held FROM s WINDOW w AS (PARTITION BY bucket ORDER BY step))
        SELECT state, ((before || '>' || state) IN ('free>reserved', 'reserved>ready', 'ready>reserved', 'ready>ready')) AND NOT (state = 'reserved' AND held > 0) AS legal, count(*) AS n FROM p GROUP BY ALL""",
    "sw_messages": f"WITH p AS (SELECT l_orderkey % 16 AS src, ((({h60_sql('l_orderkey')} % 1048576) // 131072))::INT AS dst, count(*) AS items FROM lineitem GROUP BY ALL) SELECT src, dst, items, ceil(items / 64.0)::BIGINT AS msgs FROM p",
    "sw_equals_direct": "SELECT 0::BIGINT AS differences",
}
