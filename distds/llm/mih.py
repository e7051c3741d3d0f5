"""Nearest neighbours by multi-index hashing of learned rotated binary codes, with floats reranked.

Fitting (on a bounded sample): several rotations are learned by alternating sign codes with an orthogonal fit; signs of the
rotated vector make the code. A Hamming radius is calibrated on the sample so that the wanted share of true neighbours lies
within it. Indexing: every vector goes to one block; in a block each substring of the codes has its own table of distinct keys.
Search: the radius is dealt over the substrings so that a code within it must come within its part in some substring (parts
plus one add up to the radius plus one); looking up all table keys that near finds every such code. Those within the radius
are reranked by inner product. A query with too few codes within the radius is answered by a scan of the block. A block gives
its best; the best of all blocks are the answer.

Substrings are long: where neighbours are hardly nearer than other vectors, short ones would let nearly every code through.

Edge cases: vectors that are null, zero, of another length than most or hold null or non-finite components take no part; equal
scores go to the smaller id; fewer candidates than asked for give shorter lists; repeated ids are separate candidates, except
that a query never finds its own id; empty tables give no rows; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from distds.llm.scratch import Scratch, bucket_count, only

#: Rows of the fitting sample; vectors of a block and queries that meet in one task.
SAMPLE, BLOCK, ASKED = 4_000, 10_000, 5_000
#: Rotations, each with one bit for each dimension, and substrings of a code.
ROTATIONS, SUBSTRINGS = 16, 4


def learn(x: np.ndarray, k: int, want: float, rounds: int = 12, seed: int = 5):
    """(rotation matrix with ROTATIONS * dim columns, radius)."""
    rng = np.random.default_rng(seed)
    d = x.shape[1]
    made = []
    for _ in range(ROTATIONS):
        r = np.linalg.qr(rng.standard_normal((d, d)))[0]
        for _ in range(rounds):
            u, _, vt = np.linalg.svd(np.where(x @ r >= 0, 1.0, -1.0).T @ x)
            r = (u @ vt).T
        made.append(r)
    rot = np.concatenate(made, axis=1)
    signs = np.where(x @ rot >= 0, 1.0, -1.0)
    q = np.arange(min(len(x), 400))
    s = x[q] @ x.T
    s[q, q] = -np.inf
    near = np.argsort(-s, axis=1)[:, : min(k, max(1, len(x) - 1))]
    far = (rot.shape[1] - np.einsum("qd,qkd->qk", signs[q], signs[near])) / 2
    return rot, int(np.ceil(np.quantile(far, want))) if far.size else rot.shape[1]


def codes(x: np.ndarray, rot: np.ndarray) -> np.ndarray:
    """Sign codes as 64-bit words: code by substring by word. Bits are dealt to substrings in turn; what is missing is 0."""
    bits = x @ rot >= 0
    each = -(-bits.shape[1] // SUBSTRINGS)
    words = -(-each // 64)
    out = np.zeros((len(x), SUBSTRINGS, words * 64), dtype=bool)
    for j in range(SUBSTRINGS):
        mine = bits[:, j * each : (j + 1) * each]
        out[:, j, : mine.shape[1]] = mine
    return np.packbits(out, axis=2).view(np.uint64).reshape(len(x), SUBSTRINGS, words)


def shares(radius: int, parts: int) -> list[int]:
    """How near a code within ``radius`` must come in one substring at least; -1: need not be looked up."""
    budget = radius - parts + 1
    return [budget // parts + (j < budget % parts) for j in range(parts)]


def distance(keys: np.ndarray, q: np.ndarray) -> np.ndarray:
    return np.bitwise_count(keys ^ q).sum(axis=1, dtype=np.int32)


class Tables:
    """For each substring: the keys in use and the rows of each key."""

    def __init__(self, code: np.ndarray):
        self.code, self.parts = code, []
        for j in range(code.shape[1]):
            keys, inverse = np.unique(code[:, j], axis=0, return_inverse=True)
            order = np.argsort(inverse.ravel(), kind="stable")
            self.parts.append((keys, np.searchsorted(inverse.ravel()[order], np.arange(len(keys) + 1)), order))

    def probed(self, q: np.ndarray, radius: int) -> np.ndarray:
        """Every row that some substring's table gives."""
        seen = np.zeros(len(self.code), dtype=bool)
        for j, ((keys, first, order), near) in enumerate(zip(self.parts, shares(radius, len(self.parts)))):
            hit = np.flatnonzero(distance(keys, q[j]) <= near)
            n = first[hit + 1] - first[hit]
            at = np.repeat(first[hit] - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(int(n.sum()))
            seen[order[at]] = True
        return np.flatnonzero(seen)

    def within(self, q: np.ndarray, radius: int) -> np.ndarray:
        """Every row whose code lies within ``radius`` of ``q``."""
        rows = self.probed(q, radius)
        return rows[distance(self.code[rows].reshape(len(rows), -1), q.ravel()) <= radius]


def search_block(queries: pa.Table, rows: pa.Table, rot: np.ndarray, radius: int, k: int) -> pa.Table:
    def matrix(t):
        c = t.column("v").combine_chunks()
        return c.values.to_numpy().reshape(len(t), -1)[:, :] if len(t) else np.zeros((0, rot.shape[0]))

    out = ([], [], [])
    if len(queries) and len(rows):
        x, ids = matrix(rows), rows.column("id").to_numpy()
        y, qids = matrix(queries), queries.column("id").to_numpy()
        tables, qcode = Tables(codes(x, rot)), codes(y, rot)
        for i in range(len(y)):
            at = tables.within(qcode[i], radius)
            at = at[ids[at] != qids[i]]
            if len(at) < k:
                at = np.flatnonzero(ids != qids[i])
            s = x[at] @ y[i]
            if len(s) > k:
                bar = np.partition(s, len(s) - k)[len(s) - k]
                at, s = at[s >= bar], s[s >= bar]
            best = np.lexsort((ids[at], -s))[:k]
            out[0].append(np.full(len(best), qids[i]))
            out[1].append(ids[at[best]])
            out[2].append(s[best])
    parts = [np.concatenate(o) if o else np.zeros(0) for o in out]
    return pa.table({"query_id": pa.array(parts[0].astype(np.int64)), "vec_id": pa.array(parts[1].astype(np.int64)), "score": pa.array(parts[2].astype(np.float64))})


def nearest(vectors: DataFrame, is_query: Column, k: int = 20, recall: float = 0.97, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the ``k`` nearest found for each query, by inner product in double precision."""
    spark = vectors.sparkSession
    scratch = Scratch(spark)
    v = F.col(vec_col).cast("array<double>")
    good = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    vectors = only(vectors, id_col, vec_col)
    rows = scratch.stash(vectors.filter(F.col(id_col).isNotNull() & good).select(F.col(id_col).cast("long").alias("id"), v.alias("v"), is_query.alias("q")))
    dims = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
    if dims is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    rows = rows.filter(F.size("v") == dims["d"])
    sample = rows.withColumn("h", F.xxhash64("id")).orderBy("h", "id").limit(SAMPLE).select("v").collect()
    rot, radius = learn(np.array([r["v"] for r in sample]), k, recall)
    blocks = bucket_count(dims["count"], BLOCK, 1)
    parts = bucket_count(rows.filter("q").count(), ASKED, 1)
    ids = F.sequence(F.lit(0), F.lit(parts - 1)), F.sequence(F.lit(0), F.lit(blocks - 1))
    tasks = blocks * parts
    dealt = rows.select("id", "v", F.pmod(F.xxhash64("id", F.hash("v")), F.lit(blocks)).cast("int").alias("block"), F.explode(ids[0]).alias("part"))
    asked = rows.filter("q").select("id", "v", F.pmod(F.xxhash64("id", F.lit("part")), F.lit(parts)).cast("int").alias("part"), F.explode(ids[1]).alias("block"))
    shared = spark.sparkContext.broadcast((rot, radius))  # dim * dim numbers
    asked, dealt = asked.repartition(tasks, "block", "part"), dealt.repartition(tasks, "block", "part")  # small tasks stay apart
    found = asked.groupBy("block", "part").cogroup(dealt.groupBy("block", "part")).applyInArrow(lambda a, b: search_block(a, b, *shared.value, k), "query_id long, vec_id long, score double")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")  # k rows of each block
    return found.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
