"""Quality classifier: hashed word n-grams, logistic regression, follow-the-regularised-leader updates.

Features are unigrams and bigrams of folded words and of word shapes (case, punctuation at the end, repetition of the word
before), hashed to ``2**BITS`` weights and scaled to unit length by document. Training needs at most ``MAX_TRAIN`` labelled rows
(a documented bound: those with the smallest id hashes); it runs in one task on their features. Scores are sparse dot products.

Edge cases: null and empty texts have the bias feature alone; labels that are null or repeated are taken by their maximum; rows
without a usable label are scored and not learnt from; with no labelled row every score is 0.5; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from distds.llm import textkernels as tk
from distds.llm.scratch import Scratch, only

BITS = 18
MAX_TRAIN = 8_000
ALPHA, BETA, L1, L2 = 0.6, 1.0, 0.001, 0.001
#: Passes over the training rows: more for few rows, between these bounds, for about this many updates.
EPOCHS, UPDATES = (3, 30), 24_000
#: Classes of bytes: lower, upper, digit, sentence marks, other signs, bytes of non-ASCII letters.
CLASS = np.full(256, 4, dtype=np.uint64)
CLASS[97:123], CLASS[65:91], CLASS[48:58], CLASS[128:] = 0, 1, 2, 5
CLASS[[33, 44, 46, 58, 59, 63]] = 3


def features(run: list[bytes]):
    """For each text: (distinct feature indices, values of unit length)."""
    data, starts, ends, cuts = tk.words(run, fold=False)
    folded = tk.word_hashes(tk.FOLD[data], starts, ends)
    n = (ends - starts).astype(np.uint64)
    first, last = CLASS[data[starts]], CLASS[data[ends - 1]]
    before = CLASS[data[np.maximum(ends - 2, starts)]]
    letters = np.concatenate(([0], np.cumsum(CLASS[data] == 1)))
    shout = (letters[ends] - letters[starts]) * 2 > (ends - starts)
    again = np.zeros(len(starts), dtype=np.uint64)
    again[1:] = folded[1:] == folded[:-1]
    again[cuts[:-1][cuts[:-1] < len(starts)]] = 0
    shape = tk.mix64((((first * np.uint64(8) + last) * np.uint64(8) + before) * np.uint64(2) + shout) * np.uint64(2) + again + np.uint64(1))
    length = tk.mix64(np.minimum(n, np.uint64(12)) + np.uint64(977))
    mask = np.uint64((1 << BITS) - 1)
    for i in range(len(run)):
        a, b = cuts[i], cuts[i + 1]
        s, w = shape[a:b], folded[a:b]
        grams = [np.array([7], np.uint64), s, length[a:b], w]
        if b - a > 1:
            grams += [tk.mix64(s[:-1] * tk.STEP + s[1:]), tk.mix64(w[:-1] * tk.STEP + w[1:])]
        weight = np.repeat([1.0, 1.0, 0.5, 0.3, 1.0, 0.3][: len(grams)], [len(g) for g in grams])
        at, inverse = np.unique(np.concatenate(grams) & mask, return_inverse=True)
        v = np.sqrt(np.bincount(inverse, weights=weight))
        yield at.astype(np.int32), (v / np.sqrt((v * v).sum())).astype(np.float32)


def train(table: pa.Table) -> pa.Table:
    """FTRL-proximal over the rows in the order of their hash, several epochs; returns the weights as bytes."""
    z, g2, w = np.zeros(1 << BITS), np.zeros(1 << BITS), np.zeros(1 << BITS)
    order = np.argsort(table.column("h").to_numpy(), kind="stable")
    at = [np.frombuffer(x, np.int32) for x in table.column("at").to_pylist()]
    v = [np.frombuffer(x, np.float32) for x in table.column("v").to_pylist()]
    y = table.column("y").to_numpy()
    for _ in range(min(EPOCHS[1], max(EPOCHS[0], UPDATES // max(1, len(order))))):
        for i in order:
            j, x = at[i], v[i].astype(np.float64)
            zj, gj = z[j], g2[j]
            wj = np.where(np.abs(zj) <= L1, 0.0, (np.sign(zj) * L1 - zj) / ((BETA + np.sqrt(gj)) / ALPHA + L2))
            p = 1.0 / (1.0 + np.exp(-np.clip(wj @ x, -30, 30)))
            g = (p - y[i]) * x
            z[j] = zj + g - (np.sqrt(gj + g * g) - np.sqrt(gj)) / ALPHA * wj
            g2[j] = gj + g * g
    w = np.where(np.abs(z) <= L1, 0.0, (np.sign(z) * L1 - z) / ((BETA + np.sqrt(g2)) / ALPHA + L2))
    return pa.table({"w": pa.array([w.astype(np.float32).tobytes()], pa.binary())})


def featurise(batches):
    for batch in batches:
        pairs = [x for _, run in tk.runs_of(batch.column("text")) for x in features(run)]
        yield pa.RecordBatch.from_arrays([batch.column("h"), batch.column("y"), pa.array([a.tobytes() for a, _ in pairs], pa.binary()), pa.array([v.tobytes() for _, v in pairs], pa.binary())], names=["h", "y", "at", "v"])


def scores(batches, weights: bytes, text: str):
    w = np.frombuffer(weights, np.float32).astype(np.float64)
    for batch in batches:
        s = [float(w[a] @ v) for _, run in tk.runs_of(batch.column(text)) for a, v in features(run)]
        out = 1.0 / (1.0 + np.exp(-np.clip(np.array(s, dtype=np.float64), -30, 30)))
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out)], names=[*batch.schema.names, "score"])


def fit(docs: DataFrame, labels: DataFrame, most: int = MAX_TRAIN) -> bytes:
    """Weights learnt from ``docs`` (doc_id, text) and ``labels`` (doc_id, y: 0 or 1)."""
    scratch = Scratch(docs.sparkSession)
    docs, labels = only(docs, "doc_id", "text"), only(labels, "doc_id", "y")
    labels = labels.filter("doc_id is not null and y is not null").groupBy("doc_id").agg(F.max("y").cast("int").alias("y"))
    chosen = scratch.stash(labels.withColumn("h", F.xxhash64("doc_id")).orderBy("h", "doc_id").limit(most))
    slim = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("h", "y", "text")  # at most ``most`` rows
    made = scratch.stash(slim.mapInArrow(featurise, "h long, y int, at binary, v binary"))
    got = made.withColumn("all", F.lit(1)).groupBy("all").applyInArrow(train, "w binary").collect()
    scratch.drop(made, chosen)
    return got[0]["w"] if got else np.zeros(1 << BITS, np.float32).tobytes()


def score(docs: DataFrame, weights: bytes) -> DataFrame:
    """``docs`` with the column ``score`` added; any column named so is replaced."""
    docs = docs.drop("score")
    names, at = docs.columns, docs.columns.index("text")
    own = docs.toDF(*[f"c{i}" for i in range(len(names))])  # names may clash in case
    shared = docs.sparkSession.sparkContext.broadcast(weights)  # one megabyte, whatever the input
    schema = T.StructType([*own.schema.fields, T.StructField("score", T.DoubleType())])
    return own.mapInArrow(lambda it: scores(it, shared.value, f"c{at}"), schema).toDF(*names, "score")
