"""Balanced sharding by label propagation: linked documents move towards their neighbours' shards under byte quotas.

Links come as hubs (here: equal texts), which stand for all edges among their members without listing them. Each round a hub
names the shard that already holds most of its bytes and still has room; members elsewhere ask to move; requests are admitted
in a fixed order until the quota is used up, a request larger than the room in part. Documents without links carry no edges, so
they are dealt last, to even out the sizes. A hub larger than a shard is spread over as few shards as the quotas allow.

Edge cases: a null text has no bytes, crc32 0 and no links; equal rows are told apart only by slot; empty tables give no rows;
other columns are ignored. Plain DataFrame operations throughout.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from distds.llm.scratch import Scratch, bucket_count, only, running_total, unit


#: Documents without links are dealt in classes by size, as shares of an even shard.
CLASSES = (1 / 16, 1 / 128, 1 / 1024)


def by_shard(values: list[float], shard: Column) -> Column:
    """One of a few numbers by shard."""
    return F.element_at(F.array(*[F.lit(float(v)) for v in values]), shard + 1)


def gaps_to(filled: list[float], pool: float) -> list[float]:
    """What each shard gets when ``pool`` raises the emptiest ones to one level."""
    level, order = 0.0, sorted(filled)
    for i in range(len(order)):
        level = (pool + sum(order[: i + 1])) / (i + 1)
        if i + 1 == len(order) or level <= order[i + 1]:
            break
    return [max(0.0, level - f) for f in filled]


def propagate(scratch: Scratch, linked: DataFrame, shards: int, quota: float, rounds: int) -> DataFrame:
    """``linked``: hub, h, size, shard and others; returns it with new shards, none above ``quota`` by more than chance."""
    for step in range(rounds):
        held = scratch.stash(linked.groupBy("hub", "shard").agg(F.sum("size").alias("w")))
        load = {r["shard"]: r["w"] for r in held.groupBy("shard").agg(F.sum("w").alias("w")).collect()}
        room = [quota - float(load.get(s) or 0) for s in range(shards)]
        first = Window.partitionBy("hub").orderBy(F.desc("w"), "shard")  # a hub has a row for each shard at most
        goal = held.filter(by_shard(room, F.col("shard")) > 0).withColumn("k", F.row_number().over(first)).filter("k = 1")
        goal = goal.select("hub", F.col("shard").alias("to"), F.col("w").alias("to_w"))
        asks = held.join(goal, "hub").filter((F.col("shard") != F.col("to")) & (F.col("w") <= F.col("to_w")))
        asks = asks.withColumn("b", F.pmod(F.xxhash64("hub"), F.lit(256)).cast("int"))
        asks = running_total(asks, "w", ["hub", "shard"], ["to"], "b", "before")
        share = (by_shard(room, F.col("to")) - F.col("before")) / F.col("w")
        moves = asks.select("hub", "shard", "to", share.alias("part")).filter("part > 0")
        moves = scratch.stash(moves)
        if not moves.head(1):
            break
        go = F.coalesce(unit(F.xxhash64("h", F.lit(step))) < F.col("part"), F.lit(False))
        linked = scratch.stash(linked.join(moves, ["hub", "shard"], "left").withColumn("shard", F.when(go, F.col("to")).otherwise(F.col("shard"))).drop("to", "part"))
    return linked


def shard_documents(docs: DataFrame, shards: int = 24, rounds: int = 4) -> DataFrame:
    """doc_id, size, text_crc32, law ('bytes'), shard, slot, grown_shard (null) and ``hub`` for every row."""
    scratch = Scratch(docs.sparkSession)
    docs = only(docs, "doc_id", "text")
    nodes = docs.select("doc_id", (F.coalesce(F.octet_length("text"), F.lit(0)) + 8).cast("long").alias("size"), F.coalesce(F.crc32("text"), F.lit(0)).cast("long").alias("text_crc32"), F.md5("text").alias("hub"))
    nodes = scratch.stash(nodes.withColumn("h", F.xxhash64("doc_id", "text_crc32")))
    hubs = scratch.stash(nodes.filter("hub is not null").groupBy("hub").count().filter("count > 1").select("hub", F.lit(True).alias("tied")))
    nodes = scratch.stash(nodes.join(hubs, "hub", "left").withColumn("tied", F.coalesce("tied", F.lit(False))).withColumn("shard", F.pmod(F.col("h"), F.lit(shards)).cast("int")))
    r = nodes.agg(F.count("*").alias("n"), F.sum("size").alias("s")).first()
    n, even = r["n"], (r["s"] or 0) / shards
    linked = propagate(scratch, nodes.filter("tied").drop("tied"), shards, even, rounds)

    load = {r["shard"]: r["w"] for r in linked.groupBy("shard").agg(F.sum("size").alias("w")).collect()}  # one row for each shard
    over = by_shard([max(0.0, 1 - even / max(load.get(s) or 0, 1)) for s in range(shards)], F.col("shard"))
    linked = linked.withColumn("free", unit(F.xxhash64("h", F.lit("over"))) < over)
    spare = scratch.stash(nodes.filter("not tied").drop("tied").withColumn("free", F.lit(True)).unionByName(linked))
    b = bucket_count(n)
    loose = spare.filter("free").withColumn("b", F.pmod(F.col("h"), F.lit(b)).cast("int"))
    grade = F.lit(len(CLASSES))
    for i, c in reversed(list(enumerate(CLASSES))):
        grade = F.when(F.col("size") > F.lit(c * even), F.lit(i)).otherwise(grade)
    loose = loose.withColumn("grade", grade)
    loose = scratch.stash(running_total(loose, "size", ["h", "doc_id", "size"], ["grade"], "b", "before"))
    pools = {r["grade"]: float(r["w"]) for r in loose.groupBy("grade").agg(F.sum("size").alias("w")).collect()}  # one row for each class
    filled = {r["shard"]: float(r["w"]) for r in spare.filter("not free").groupBy("shard").agg(F.sum("size").alias("w")).collect()}
    filled, done = [filled.get(s, 0.0) for s in range(shards)], [spare.filter("not free").drop("free")]
    for i, pool in sorted(pools.items()):
        gaps, edge, ends = gaps_to(filled, pool), 0.0, []
        for g in gaps:
            edge += g
            ends.append(edge)
        at = F.col("before") + F.col("size") / 2
        place = F.lit(max(s for s in range(shards) if gaps[s] > 0))
        for s in reversed(range(shards)):
            if gaps[s] > 0:
                place = F.when(at < F.lit(ends[s]), F.lit(s)).otherwise(place)
        dealt = loose.filter(F.col("grade") == i).withColumn("shard", place.cast("int"))
        done.append(dealt.drop("before", "b", "grade", "free"))
        for r in dealt.groupBy("shard").agg(F.sum("size").alias("w")).collect():
            filled[r["shard"]] += float(r["w"])
    every = done[0]
    for d in done[1:]:
        every = every.unionByName(d)
    placed = scratch.stash(every.withColumn("b", F.pmod(F.col("h"), F.lit(max(8, b // shards))).cast("int")).withColumn("one", F.lit(1)))
    out = running_total(placed, "one", ["h", "doc_id", "size"], ["shard"], "b", "slot")
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "hub")
