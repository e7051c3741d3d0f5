"""Best-fit packing into bins of several permitted lengths.

Texts longer than the largest length are cut into pieces of that length. Pieces are dealt to shards of bounded size by hash;
in a shard the longest go first. A piece goes to the open bin with the least room that still takes it; if none does, a bin is
opened with the permitted length whose expected cost for each packed token is least, given the pieces still to come. In the end
every bin shrinks to the least permitted length that holds its contents.

Edge cases: null and empty texts have no words and make no piece; ties go by doc_id and piece; repeated rows are packed one by
one; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import bisect

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from distds.llm.scratch import Scratch, bucket_count, only, word_count

LENGTHS = (256, 512, 1024, 2048)
#: Pieces in a shard, about.
SHARD = 20_000
#: Cost of a bin: a fixed part, one for each place, and a part that grows with the square (attention).
FIXED, SQUARE = 16.0, 1.0 / 16384
OUT = "doc_id long, piece int, start long, length int, bin string, capacity int, at int"


def cost(capacity: int) -> float:
    return FIXED + capacity + SQUARE * capacity * capacity


def expected(room: int, lens: list[int], left: np.ndarray) -> int:
    """Tokens that pieces still to come will bring into ``room``, taking the longest that fits each time."""
    got = 0
    for _ in range(8):
        i = bisect.bisect_right(lens, room) - 1
        while i >= 0 and left[i] <= 0:
            i -= 1
        if i < 0:
            break
        got, room = got + lens[i], room - lens[i]
    return got


def pack(lengths: np.ndarray, capacities=LENGTHS):
    """(bin of each piece, offset of each piece, capacity of each bin) for pieces sorted by falling length."""
    caps = sorted(capacities)
    lens = np.unique(lengths).tolist()
    slot = {x: i for i, x in enumerate(lens)}
    left = np.bincount([slot[x] for x in lengths.tolist()], minlength=len(lens)) if len(lengths) else np.zeros(0, int)
    rooms: list[int] = []  # sorted room of open bins, with stacks of bins by room
    stack: dict[int, list[int]] = {}
    used: list[int] = []
    size: list[int] = []
    bins, at = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    for i, x in enumerate(lengths.tolist()):
        left[slot[x]] -= 1
        j = bisect.bisect_left(rooms, x)
        if j < len(rooms):
            r = rooms[j]
            b = stack[r].pop()
            if not stack[r]:
                del stack[r]
                rooms.pop(j)
        else:
            c = min((c for c in caps if c >= x), key=lambda c: cost(c) / (x + expected(c - x, lens, left)))
            b, r = len(used), c
            used.append(0)
            size.append(c)
        bins[i], at[i] = b, used[b]
        used[b] += x
        r -= x
        if r:
            if r not in stack:
                bisect.insort(rooms, r)
                stack[r] = []
            stack[r].append(b)
    return bins, at, np.array([next(c for c in caps if c >= u) for u in used], dtype=np.int64)


def pack_shard(table: pa.Table, capacities) -> pa.Table:
    table = table.sort_by([("length", "descending"), ("doc_id", "ascending"), ("piece", "ascending")])
    bins, at, caps = pack(table.column("length").to_numpy(), capacities)
    shard = table.column("shard")[0].as_py()
    names = pa.array([f"{shard}-{b}" for b in bins], pa.string())
    cols = [table.column(c) for c in ("doc_id", "piece", "start", "length")]
    return pa.table([*cols, names, pa.array(caps[bins], pa.int32()), pa.array(at, pa.int32())], names=["doc_id", "piece", "start", "length", "bin", "capacity", "at"])


def best_fit(docs: DataFrame, capacities=LENGTHS) -> DataFrame:
    """One row for each piece: doc_id, piece, start and length in words, bin, its capacity, and the place in it."""
    scratch = Scratch(docs.sparkSession)
    most = max(capacities)
    sizes = scratch.stash(only(docs, "doc_id", "text").select("doc_id", word_count(F.col("text")).alias("n"), F.hash("text").alias("t")).filter("n > 0"))
    pieces = sizes.select("doc_id", "t", "n", F.explode(F.sequence(F.lit(0), F.floor((F.col("n") - 1) / most).cast("int"))).alias("piece"))
    start = F.col("piece").cast("long") * most
    shards = bucket_count(int(sizes.agg(F.sum(F.ceil(F.col("n") / most))).first()[0] or 0), SHARD, 1)
    pieces = pieces.select("doc_id", "piece", start.alias("start"), F.least(F.lit(most), F.col("n") - start).cast("int").alias("length"), F.pmod(F.xxhash64("doc_id", "t", "piece"), F.lit(shards)).cast("int").alias("shard"))
    pieces = pieces.repartition(2 * shards, "shard")  # shards are tiny in bytes and would be merged into a few tasks
    return pieces.groupBy("shard").applyInArrow(lambda t: pack_shard(t, capacities), OUT)
