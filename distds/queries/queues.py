"""Phase queues and rings on the event log."""

from __future__ import annotations

from pyspark.sql import functions as F

from distds.operators.queues import PhaseQueue, RingQueue, ready, ready_fault, vector_log
from distds.plans.promises import Promise
from distds.sources.io import settle, table

CAP, MANY, HOSTS, CHUNK = 64, 20, 8, 2000


def log(spark, d, hosts: int | None = None):
    host = F.lit(0).cast("long") if hosts is None else (F.col("user_id") % hosts)
    op = F.when(F.col("event_type").isin("signup", "error"), "pop").otherwise("push")
    return table(spark, d, "events").select(host.alias("host"), F.col("event_id").alias("seq"), op.alias("op"), F.col("event_id").alias("item"))


def pushes(spark, d, hosts=None):
    return log(spark, d, hosts).filter("op = 'push'").select("host", "seq", "item")


def pops(spark, d, hosts=None):
    return log(spark, d, hosts).filter("op = 'pop'").select("host", "seq")


def pq_push(spark, d):
    return PhaseQueue.create(spark, 4000).push(pushes(spark, d))[1]


def pq_many(spark, d):
    return PhaseQueue.create(spark, 400).push(pushes(spark, d, HOSTS))[1]


def pq_pop(spark, d, hosts=None, cls=PhaseQueue, cap=4000):
    q, _ = cls.create(spark, cap).push(pushes(spark, d, hosts))
    q = type(q)(settle(q.items), settle(q.bounds), q.capacity)
    return q.pop(pops(spark, d, hosts))[1].select("host", "seq", "ok", "pos", "item")


def pq_refreshes(spark, d):
    q = PhaseQueue.create(spark, 400)
    return q.refreshes(q.push(pushes(spark, d, HOSTS))[1])


def vectors(spark, d):
    li = table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("n"))
    return li.select((F.col("l_orderkey") % HOSTS).alias("host"), F.col("l_orderkey").alias("seq"), F.when(F.col("l_orderkey") % 3 == 2, "pop").otherwise("push").alias("op"), "n")


def pq_push_vec(spark, d):
    return vector_log(vectors(spark, d).filter("op = 'push'"), 1000).select("host", "seq", "ok", "pos")


def pq_pop_vec(spark, d):
    """A phase of vector pushes, then one of vector pops: the order is by phase and then by seq."""
    v = vectors(spark, d).withColumn("seq", F.col("seq") + F.when(F.col("op") == "pop", 1 << 40).otherwise(0))
    return vector_log(v, 1000).filter("op = 'pop'").select("host", "seq", "ok", "pos")


def rq_vec(spark, d):
    return vector_log(vectors(spark, d), 64).select("host", "seq", "op", "ok", "pos")


def ring(spark, d, hosts, cap):
    return RingQueue.create(spark, cap).run_log(log(spark, d, hosts), rows=CHUNK)


def rq_push_pushpop(spark, d):
    return ring(spark, d, None, CAP).filter("op = 'push'").select("host", "seq", "ok", "pos")


def rq_pop_pushpop(spark, d):
    return ring(spark, d, None, CAP).filter("op = 'pop'").select("host", "seq", "ok", "pos", "item")


def rq_many_pushpop(spark, d):
    return ring(spark, d, HOSTS, MANY)


def rq_push_push(spark, d):
    return RingQueue.create(spark, 4000).run_log(log(spark, d).filter("op = 'push'"), Promise.PUSH).select("host", "seq", "ok", "pos")


def rq_many_push(spark, d):
    return RingQueue.create(spark, 400).run_log(log(spark, d, HOSTS).filter("op = 'push'"), Promise.PUSH).select("host", "seq", "ok", "pos")


def rq_pop_pop(spark, d):
    return pq_pop(spark, d, None, RingQueue)


def filled(spark, d):
    return RingQueue.create(spark, 700).push(pushes(spark, d, HOSTS))[0]


def rq_local_pop(spark, d):
    return filled(spark, d).local_pop(3, 100)


def rq_resize(spark, d):
    return filled(spark, d).resize(1000).slots()


def rq_migrate(spark, d):
    where = spark.createDataFrame([(1, 101), (2, 102)], "host long, new_host long")
    return filled(spark, d).migrate(where).items


def rq_drain(spark, d):
    got = filled(spark, d).drain()
    return got.select("host", F.size("items").cast("long").alias("n"), F.element_at("items", 1).alias("first"), F.element_at("items", -1).alias("last"))


def held(spark, d):
    """Rings for 120 items of which the first pushes have filled up to 100."""
    q = RingQueue.create(spark, 100).push(pushes(spark, d, HOSTS))[0].resize(120)
    return RingQueue(settle(q.items), settle(q.bounds), q.capacity)


def rq_filled_pushpop(spark, d):
    """A mixed log on queues that hold items."""
    return held(spark, d).run_log(log(spark, d, HOSTS), rows=CHUNK)


def rq_filled_pop_pop(spark, d):
    return held(spark, d).run_log(log(spark, d, HOSTS).filter("op = 'pop'"), Promise.POP)


def rq_filled_push_push(spark, d):
    return held(spark, d).run_log(log(spark, d, HOSTS).filter("op = 'push'"), Promise.PUSH)


def rq_local_push(spark, d):
    """Hosts append to their own queues, which hold items already."""
    q = held(spark, d)
    return q.local_push(q.place_local(pushes(spark, d, HOSTS), HOSTS), HOSTS)[1]


def rq_vec_items(spark, d):
    """Vectors with their items: what each pop of a vector returns, its items in order as text."""
    v = vectors(spark, d).withColumn("items", F.when(F.col("op") == "push", F.transform(F.sequence(F.lit(1).cast("long"), "n"), lambda j: F.col("seq") * 100 + j)))
    got = RingQueue.create(spark, 64).apply_vectors(v, rows=CHUNK)[1]
    return got.filter("op = 'pop'").select("host", "seq", "ok", "pos", F.array_join(F.col("items").cast("array<string>"), ",").alias("items"))


def ready_log(spark, d):
    e = table(spark, d, "events")
    pos = F.col("event_id") - e.agg(F.min("event_id")).first()[0]
    return e.select(F.lit(0).cast("long").alias("host"), pos.alias("pos"), (F.unix_micros(F.col("ts").cast("timestamp")) + F.round(F.col("value") * 1_000_000).cast("long") * 60).alias("done_at"))


def rq_ready(spark, d):
    return ready(ready_log(spark, d))


def rq_ready_fault(spark, d):
    return ready_fault(ready_log(spark, d)).agg(F.count("*").alias("early"))


QUERIES = {f.__name__: f for f in (pq_push, pq_push_vec, pq_pop, pq_pop_vec, pq_many, pq_refreshes, rq_push_pushpop, rq_push_push, rq_pop_pushpop, rq_pop_pop, rq_many_pushpop, rq_many_push, rq_vec, rq_local_pop, rq_resize, rq_migrate, rq_drain, rq_ready, rq_ready_fault, rq_filled_pushpop, rq_filled_pop_pop, rq_filled_push_push, rq_local_push, rq_vec_items)}


def events_sql(hosts=None):
    host = "0::BIGINT" if hosts is None else f"user_id % {hosts}"
    return f"log AS (SELECT {host} AS host, event_id AS seq, CASE WHEN event_type IN ('signup', 'error') THEN 'pop' ELSE 'push' END AS op, event_id AS item FROM events)"


def single_sql(hosts, cap, slot=False):
    extra = f", CASE WHEN k < {cap} THEN k % {cap} END AS slot" if slot else ""
    return f"WITH {events_sql(hosts)}, p AS (SELECT host, seq, row_number() OVER (PARTITION BY host ORDER BY seq) - 1 AS k FROM log WHERE op = 'push') SELECT host, seq, k < {cap} AS ok, CASE WHEN k < {cap} THEN k END AS pos{extra} FROM p"


def pop_sql(hosts, cap):
    return f"""WITH {events_sql(hosts)}, p AS (SELECT host, item, row_number() OVER (PARTITION BY host ORDER BY seq) - 1 AS k FROM log WHERE op = 'push'),
        q AS (SELECT host, seq, row_number() OVER (PARTITION BY host ORDER BY seq) - 1 AS k FROM log WHERE op = 'pop')
        SELECT q.host, q.seq, p.k IS NOT NULL AS ok, p.k AS pos, p.item FROM q LEFT JOIN p ON p.host = q.host AND p.k = q.k AND p.k < {cap}"""


def replay_sql(hosts, cap):
    return f"""{events_sql(hosts)}, o AS (SELECT *, row_number() OVER (PARTITION BY host ORDER BY seq) AS k FROM log),
        run AS (SELECT host, k, seq, op, item, op = 'push' AS ok, 0::BIGINT AS head, 0::BIGINT AS tail FROM o WHERE k = 1
            UNION ALL SELECT o.host, o.k, o.seq, o.op, o.item, CASE WHEN o.op = 'push' THEN t - h < {cap} ELSE t > h END, h, t FROM
                (SELECT host, k, CASE WHEN ok AND op = 'pop' THEN head + 1 ELSE head END AS h, CASE WHEN ok AND op = 'push' THEN tail + 1 ELSE tail END AS t FROM run) r
                JOIN o ON o.host = r.host AND o.k = r.k + 1),
        done AS (SELECT host, seq, op, item, ok, CASE WHEN NOT ok THEN NULL WHEN op = 'push' THEN tail ELSE head END AS pos FROM run),
        out AS (SELECT d.host, d.seq, d.op, d.ok, d.pos, p.item FROM done d LEFT JOIN done p ON p.host = d.host AND p.pos = d.pos AND p.op = 'push' AND p.ok)"""


def vec_sql(cap, where="", order="l_orderkey"):
    return f"""WITH RECURSIVE v AS (SELECT l_orderkey % {HOSTS} AS host, l_orderkey AS seq, CASE WHEN l_orderkey % 3 = 2 THEN 'pop' ELSE 'push' END AS op, count(*) AS n FROM lineitem GROUP BY ALL),
        o AS (SELECT host, {order} AS seq, op, n, row_number() OVER (PARTITION BY host ORDER BY {order}) AS k FROM v {where}),
        run AS (SELECT host, k, seq, op, n, CASE WHEN op = 'push' THEN n <= {cap} ELSE false END AS ok, 0::BIGINT AS head, 0::BIGINT AS tail FROM o WHERE k = 1
            UNION ALL SELECT o.host, o.k, o.seq, o.op, o.n, CASE WHEN o.op = 'push' THEN t - h + o.n <= {cap} ELSE t - h >= o.n END, h, t FROM
                (SELECT host, k, CASE WHEN ok AND op = 'pop' THEN head + n ELSE head END AS h, CASE WHEN ok AND op = 'push' THEN tail + n ELSE tail END AS t FROM run) r
                JOIN o ON o.host = r.host AND o.k = r.k + 1)
        SELECT host, seq, op, ok, CASE WHEN NOT ok THEN NULL WHEN op = 'push' THEN tail ELSE head END AS pos FROM run"""


#: Queues of 120 that hold up to 100 items; their first op-log numbers go on from there.
HELD = f"{events_sql(HOSTS)}, p0 AS (SELECT host, item, row_number() OVER (PARTITION BY host ORDER BY seq) - 1 AS pos FROM log WHERE op = 'push'), held AS MATERIALIZED (SELECT * FROM p0 WHERE pos < 100), h0 AS MATERIALIZED (SELECT host, count(*) AS n FROM held GROUP BY 1)"
FILLED = f"""WITH RECURSIVE {HELD}, o AS (SELECT log.*, coalesce(n, 0) AS n, row_number() OVER (PARTITION BY log.host ORDER BY seq) AS k FROM log LEFT JOIN h0 USING (host)),
    run AS (SELECT host, k, seq, op, item, CASE WHEN op = 'push' THEN n < 120 ELSE n > 0 END AS ok, 0::BIGINT AS head, n AS tail FROM o WHERE k = 1
        UNION ALL SELECT o.host, o.k, o.seq, o.op, o.item, CASE WHEN o.op = 'push' THEN t - h < 120 ELSE t > h END, h, t FROM
            (SELECT host, k, CASE WHEN ok AND op = 'pop' THEN head + 1 ELSE head END AS h, CASE WHEN ok AND op = 'push' THEN tail + 1 ELSE tail END AS t FROM run) r
            JOIN o ON o.host = r.host AND o.k = r.k + 1),
    done AS (SELECT host, seq, op, item, ok, CASE WHEN NOT ok THEN NULL WHEN op = 'push' THEN tail ELSE head END AS pos FROM run),
    every AS (SELECT host, pos, item FROM held UNION ALL SELECT host, pos, item FROM done WHERE ok AND op = 'push')
    SELECT d.host, d.seq, d.op, d.ok, d.pos, e.item FROM done d LEFT JOIN every e ON e.host = d.host AND e.pos = d.pos"""


def filled_single_sql(op):
    good = "k + n < 120" if op == "push" else "k < n"
    pos = "k + n" if op == "push" else "k"
    item = "r.item" if op == "push" else "held.item"
    return f"""WITH {HELD}, r AS MATERIALIZED (SELECT log.host, seq, op, item, coalesce(n, 0) AS n, row_number() OVER (PARTITION BY log.host ORDER BY seq) - 1 AS k FROM log LEFT JOIN h0 USING (host) WHERE op = '{op}')
        SELECT r.host, r.seq, r.op, {good} AS ok, CASE WHEN {good} THEN {pos} END AS pos, CASE WHEN {good} THEN {item} END AS item FROM r LEFT JOIN held ON held.host = r.host AND held.pos = r.k"""


FILL = f"WITH {events_sql(HOSTS)}, p AS (SELECT host, item, row_number() OVER (PARTITION BY host ORDER BY seq) - 1 AS pos FROM log WHERE op = 'push'), q AS (SELECT * FROM p WHERE pos < 700)"
READY = "r AS (SELECT event_id - min(event_id) OVER () AS pos, epoch_us(ts) + round(value * 1000000)::BIGINT * 60 AS done_at FROM events)"
PHASED = "seq + CASE WHEN op = 'pop' THEN 1099511627776 ELSE 0 END"
ORACLES = {
    "pq_push": single_sql(None, 4000, True), "pq_many": single_sql(HOSTS, 400, True), "rq_push_push": single_sql(None, 4000), "rq_many_push": single_sql(HOSTS, 400),
    "pq_pop": pop_sql(None, 4000), "rq_pop_pop": pop_sql(None, 4000),
    "pq_refreshes": f"SELECT host, sum((NOT ok)::BIGINT)::BIGINT AS refreshes FROM ({single_sql(HOSTS, 400)}) GROUP BY 1",
    "rq_push_pushpop": f"WITH RECURSIVE {replay_sql(None, CAP)} SELECT host, seq, ok, pos FROM out WHERE op = 'push'",
    "rq_pop_pushpop": f"WITH RECURSIVE {replay_sql(None, CAP)} SELECT host, seq, ok, pos, item FROM out WHERE op = 'pop'",
    "rq_many_pushpop": f"WITH RECURSIVE {replay_sql(HOSTS, MANY)} SELECT host, seq, op, ok, pos, item FROM out",
    "pq_push_vec": f"SELECT host, seq, ok, pos FROM ({vec_sql(1000, where='WHERE op = ' + chr(39) + 'push' + chr(39), order='seq')})",
    "pq_pop_vec": f"SELECT host, seq, ok, pos FROM ({vec_sql(1000, order=PHASED)}) WHERE op = 'pop'",
    "rq_vec": vec_sql(64, order="seq"),
    "rq_vec_items": f"""WITH r AS (SELECT v.*, n FROM ({vec_sql(64, order="seq")}) v JOIN (SELECT l_orderkey AS seq, count(*) AS n FROM lineitem GROUP BY 1) USING (seq)),
        e AS (SELECT host, pos + j - 1 AS place, seq * 100 + j AS item FROM (SELECT host, seq, pos, unnest(range(1, n + 1)) AS j FROM r WHERE ok AND op = 'push')),
        g AS (SELECT r.host, r.seq, string_agg(item::VARCHAR, ',' ORDER BY place) AS items FROM r JOIN e ON e.host = r.host AND e.place >= r.pos AND e.place < r.pos + r.n WHERE r.ok AND r.op = 'pop' GROUP BY ALL)
        SELECT r.host, r.seq, r.ok, r.pos, g.items FROM r LEFT JOIN g ON g.host = r.host AND g.seq = r.seq WHERE r.op = 'pop'""",
    "rq_filled_pushpop": FILLED, "rq_filled_pop_pop": filled_single_sql("pop"), "rq_filled_push_push": filled_single_sql("push"),
    "rq_local_push": f"SELECT host, seq, ok, pos FROM ({filled_single_sql('push')})",
    "rq_local_pop": f"{FILL} SELECT host, pos, item FROM q WHERE host = 3 AND pos < 100",
    "rq_resize": f"{FILL} SELECT host, pos, pos % 1000 AS slot, item FROM q",
    "rq_migrate": f"{FILL} SELECT CASE host WHEN 1 THEN 101 WHEN 2 THEN 102 ELSE host END AS host, pos, item FROM q",
    "rq_drain": f"{FILL} SELECT host, count(*) AS n, arg_min(item, pos) AS first, arg_max(item, pos) AS last FROM q GROUP BY 1",
    "rq_ready": f"WITH {READY} SELECT 0::BIGINT AS host, pos, done_at, max(done_at) OVER (ORDER BY pos) AS visible_at FROM r",
    "rq_ready_fault": f"WITH {READY}, s AS (SELECT row_number() OVER (ORDER BY done_at, pos) - 1 AS pos, done_at AS shown_at FROM r) SELECT count(*) AS early FROM s JOIN r USING (pos) WHERE shown_at < done_at",
}
