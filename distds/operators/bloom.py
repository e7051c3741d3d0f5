"""Bloom filters: scattered bits, and blocks of 64 bits that make test-and-insert one step."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from distds.functions.hashing import HASHES, h60


class ScatterBloom:
    """k bits anywhere in ``bits``; finding out whether all were set before is not one step."""

    def __init__(self, bits: int, k: int = 4):
        self.bits, self.k = bits, k

    def places(self, x: Column) -> Column:
        """Distinct bits of a value."""
        return F.array_distinct(F.array(*[F.pmod(h60(x, 10 + j), F.lit(self.bits)) for j in range(self.k)]))

    def build(self, df: DataFrame) -> DataFrame:
        """word, mask with 64 bits a word, or-ed before the exchange."""
        bit = df.filter("x is not null").select(F.explode(self.places(F.col("x"))).alias("bit"))
        mask = F.expr("shiftleft(1L, cast(bit % 64 as int))")
        return bit.select(F.floor(F.col("bit") / 64).alias("word"), mask.alias("mask")).groupBy("word").agg(F.bit_or("mask").alias("mask"))

    def insert(self, df: DataFrame) -> DataFrame:
        """seq, x -> seq, present: whether every bit was set by an earlier seq. Nulls set no bit and are never present."""
        bits = df.select("seq", F.explode(self.places(F.col("x"))).alias("bit"))
        first = bits.groupBy("bit").agg(F.min("seq").alias("first"))
        early = F.coalesce(F.col("first") < F.col("seq"), F.lit(False))
        return bits.join(first, "bit", "left").groupBy("seq").agg(F.min(early).alias("present"))

    def find(self, df: DataFrame, state: DataFrame) -> DataFrame:
        """seq, x against ``build``'s words."""
        bits = df.select("seq", F.explode(self.places(F.col("x"))).alias("bit")).withColumn("word", F.floor(F.col("bit") / 64))
        hit = bits.join(state, "word", "left")
        is_set = F.expr("coalesce(mask & shiftleft(1L, cast(bit % 64 as int)), 0L) != 0")
        return hit.groupBy("seq").agg(F.min(is_set).alias("present"))


class BlockedBloom:
    """Each value sets up to k bits of one 64-bit block: one or-ed mask, one step."""

    def __init__(self, blocks: int, k: int = 4, hash_fn: str = "portable"):
        if not 1 <= k <= 10:
            raise ValueError("1 to 10 lanes")
        self.blocks, self.k, self.hash = blocks, k, HASHES[hash_fn]

    def block(self, x: Column) -> Column:
        return F.pmod(self.hash(x, 1), F.lit(self.blocks))

    def mask(self, x: Column) -> Column:
        h, out = self.hash(x, 2), F.lit(0).cast("long")
        one = F.lit(1).cast("long")
        for j in range(self.k):
            out = out.bitwiseOR(F.call_function("shiftleft", one, F.shiftright(h, 6 * j).bitwiseAND(F.lit(63)).cast("int")))
        return out

    def wide(self, words: int) -> WideBloom:
        """The filter with blocks of several words, for building and finding only: one step covers one word."""
        return WideBloom(self.blocks, self.k, words)

    def keyed(self, df: DataFrame) -> DataFrame:
        return df.select("seq", self.block(F.col("x")).alias("block"), self.mask(F.col("x")).alias("mask"))

    def insert(self, df: DataFrame, state: DataFrame | None = None) -> DataFrame:
        """seq, x -> seq, present: from strictly earlier seq and ``state``. Values stay behind; nulls are never present.

        Only the first sighting of a mask can find bits unset, so sightings are folded before they move and the ordered window
        sees each mask of a block once, however often a value repeats.
        """
        rows = self.keyed(df)
        firsts = rows.filter("block is not null").groupBy("block", "mask").agg(F.min("seq").alias("first"))
        if state is not None:
            held = state.join(firsts.select("block").distinct(), "block", "left_semi")
            firsts = firsts.union(held.select("block", "mask", F.lit(None).cast(firsts.schema["first"].dataType)))
        w = Window.partitionBy("block").orderBy(F.col("first").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, -1)
        seen = firsts.withColumn("p", F.coalesce(F.bit_or("mask").over(w), F.lit(0).cast("long"))).filter("first is not null")
        seen = seen.select("block", "mask", "first", (F.col("p").bitwiseAND(F.col("mask")) == F.col("mask")).alias("early"))
        return rows.join(seen, ["block", "mask"], "left").select("seq", F.coalesce(F.col("early") | (F.col("seq") > F.col("first")), F.lit(False)).alias("present"))

    def build(self, df: DataFrame) -> DataFrame:
        return df.filter("x is not null").select(self.block(F.col("x")).alias("block"), self.mask(F.col("x")).alias("mask")).groupBy("block").agg(F.bit_or("mask").alias("mask"))

    def find(self, df: DataFrame, state: DataFrame) -> DataFrame:
        hit = self.keyed(df).join(state.select("block", F.col("mask").alias("m")), "block", "left")
        return hit.select("seq", F.coalesce(F.coalesce(F.col("m"), F.lit(0)).bitwiseAND(F.col("mask")) == F.col("mask"), F.lit(False)).alias("present"))

    @staticmethod
    def merge(a: DataFrame, b: DataFrame) -> DataFrame:
        return a.union(b).groupBy("block").agg(F.bit_or("mask").alias("mask"))


class WideBloom:
    """Blocks of ``words`` 64-bit words: lanes pick a word too, so load evens out and the rate falls towards the flat filter's."""

    def __init__(self, blocks: int, k: int = 4, words: int = 4):
        self.inner, self.words = BlockedBloom(blocks, k), words

    def masks(self, df: DataFrame) -> DataFrame:
        """Rows of ``df`` with block, word and mask for each lane."""
        x, lanes = F.col("x"), []
        for j in range(self.inner.k):
            bit = F.shiftright(h60(x, 2), 6 * j).bitwiseAND(F.lit(63)).cast("int")
            word = F.pmod(h60(x, 20 + j), F.lit(self.words)).cast("int")
            lanes.append(F.struct(word.alias("word"), F.call_function("shiftleft", F.lit(1).cast("long"), bit).alias("mask")))
        return df.withColumn("block", self.inner.block(x)).withColumn("_l", F.explode(F.array(*lanes))).select("*", "_l.*").drop("_l")

    def build(self, df: DataFrame) -> DataFrame:
        return self.masks(df.select("x")).groupBy("block", "word").agg(F.bit_or("mask").alias("mask"))

    def find(self, df: DataFrame, state: DataFrame) -> DataFrame:
        hit = self.masks(df).join(state.select("block", "word", F.col("mask").alias("m")), ["block", "word"], "left")
        return hit.groupBy("seq").agg(F.min(F.coalesce(F.col("m"), F.lit(0)).bitwiseAND(F.col("mask")) == F.col("mask")).alias("present"))


def race_claims(df: DataFrame) -> DataFrame:
    """``df``: step, op, x, bit, a schedule of single-bit steps. x, claims: operations of a value that believe to be first.

    An operation claims to be new when one of its steps found its bit unset. More than one claim is the anomaly.
    """
    prior = Window.partitionBy("bit").orderBy("step").rowsBetween(Window.unboundedPreceding, -1)
    found = df.withColumn("unset", F.count("*").over(prior) == 0)
    ops = found.groupBy("x", "op").agg(F.max("unset").alias("claims"))
    return ops.groupBy("x").agg(F.sum(F.col("claims").cast("long")).alias("claims"))


def fpr(n: int, size: int, k: int, kind: str = "blocked") -> float:
    """Expected share of false positives with n keys; ``size``: bits (scattered) or 64-bit blocks (blocked)."""
    if kind == "scattered":
        return (1 - (1 - 1 / size) ** (k * n)) ** k
    load, total, p = n / size, 0.0, math.exp(-n / size)
    if load > 500:  # every block is full, and the sum's terms too small to add
        return (1 - (1 - 1 / 64) ** (k * load)) ** k
    for i in range(1, int(load + 12 * math.sqrt(load) + 40)):
        p *= load / i
        total += p * (1 - (1 - 1 / 64) ** (k * i)) ** k
    return total


def size_for(n: int, rate: float, k: int = 4, kind: str = "blocked") -> int:
    """The least size whose expected rate stays below ``rate``."""
    lo, hi = 1, 64
    while fpr(n, hi, k, kind) > rate:
        hi *= 2
    while lo < hi:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if fpr(n, mid, k, kind) <= rate else (mid + 1, hi)
    return lo
