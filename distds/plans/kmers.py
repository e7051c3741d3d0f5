"""k-mer counting: reads from text, extraction, exact counts, and counts behind a filter of first sightings."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from distds.functions.codecs import pack_kmer, unpack_kmer
from distds.operators.bloom import BlockedBloom, size_for
from distds.operators.keyed_table import power_of_two
from distds.sources.io import settle

LETTERS = "abcdefghijklmnopqrstuvwxyz"
BASES = "".join("ACGT"[i % 4] for i in range(26))
#: Starts of k-mers in one window of a read: substrings of long strings cost as much as the text before them.
WINDOW = 512
#: Sightings that a task folds at a time, and blocks whose masks one task merges.
CHUNK, SPAN = 1 << 20, 1 << 19
#: Sightings for each block of a filter that is sized by sightings.
LOAD = 4


def bases(text: Column, invalid: bool = False) -> Column:
    """Lower-case A-Z; each letter becomes one of four bases; anything else goes, or becomes N."""
    low = F.translate(text, LETTERS.upper(), LETTERS)
    return F.translate(F.regexp_replace(low, "[^a-z]", "n" if invalid else ""), LETTERS, BASES) if not invalid else F.translate(F.regexp_replace(low, "[^a-z]", "#"), LETTERS + "#", BASES + "N")


def reads_from_text(df: DataFrame, key: str, text: str, invalid: bool = False) -> DataFrame:
    return df.select(F.col(key).alias("read_id"), bases(F.col(text), invalid).alias("seq")).repartition(max(8, df.sparkSession.sparkContext.defaultParallelism))


def extract(reads: DataFrame, k: int, edges: bool = True) -> DataFrame:
    """read_id, p, kmer, left, right for p = 1 .. len - k + 1; letters beyond a read are null.

    Reads are cut into windows first, which carry k - 1 letters and one more on either side.
    """
    n = F.length("seq")
    starts = F.when(n >= k, F.sequence(F.lit(1), n - k + 1, F.lit(WINDOW))).otherwise(F.array().cast("array<int>"))
    cut = reads.select("read_id", "seq", n.alias("n"), F.explode(starts).alias("s"))
    cut = cut.select("read_id", "s", "n", F.substring("seq", F.greatest(F.col("s") - 1, F.lit(1)), F.lit(WINDOW + k + 1)).alias("w"), F.when(F.col("s") > 1, 1).otherwise(0).alias("pad"))
    here = F.least(F.lit(WINDOW), F.col("n") - k + 2 - F.col("s"))
    at = F.transform(F.sequence(F.lit(1), here), lambda j: F.struct((F.col("s") + j - 1).alias("p"), F.substring("w", j + F.col("pad"), F.lit(k)).alias("kmer"), *([F.when(F.col("s") + j - 1 > 1, F.substring("w", j + F.col("pad") - 1, F.lit(1))).alias("left"), F.when(F.col("s") + j - 1 + k <= F.col("n"), F.substring("w", j + F.col("pad") + k, F.lit(1))).alias("right")] if edges else [])))
    return cut.select("read_id", F.explode(at).alias("x")).select("read_id", "x.*")


def shingles(df: DataFrame, key: str, text: str, k: int) -> DataFrame:
    """Word k-grams, words split at single spaces: read_id, p, kmer."""
    words = df.select(F.col(key).alias("read_id"), F.split(text, " ").alias("w"))
    at = F.transform(F.sequence(F.lit(1), F.size("w") - k + 1), lambda i: F.struct(i.alias("p"), F.array_join(F.slice("w", i, F.lit(k)), " ").alias("kmer")))
    return words.filter(F.size("w") >= k).select("read_id", F.explode(at).alias("x")).select("read_id", "x.*")


def count_plain(kmers: DataFrame) -> DataFrame:
    return kmers.groupBy("kmer").agg(F.count("*").alias("n"))


def spectrum(counts: DataFrame) -> DataFrame:
    return counts.groupBy("n").agg(F.count("*").alias("kmers"))


def canonical(c: Column) -> Column:
    """The smaller of a k-mer and its reverse complement."""
    return F.least(c, F.translate(F.reverse(c), "ACGT", "TGCA"))


def sightings(reads: DataFrame, k: int) -> int:
    """How many k-mers the reads hold, from their lengths alone."""
    return int(reads.agg(F.sum(F.greatest(F.length("seq") - k + 1, F.lit(0)))).first()[0] or 0)


def blocks_for(n: int) -> int:
    """Blocks of a filter for at most ``n`` distinct keys: a power of two with up to LOAD keys a block."""
    return power_of_two(-(-n // LOAD))


def first_order(kmers: DataFrame) -> DataFrame:
    """Sightings in the order of reads and places, however long a read is."""
    return kmers.select("kmer", F.struct("read_id", "p").alias("seq"))


def count_bloom(kmers: DataFrame, blocks: int, k: int = 4, exact: bool = False) -> DataFrame:
    """kmer, occ, fp, hits, n: counting behind a blocked filter that absorbs the first sighting.

    Only the first occurrence of a k-mer can set bits, so the filter runs over distinct k-mers. ``fp``: the filter took the
    first sighting for a repeat. ``n`` reports hits + 1; the true count is hits + 1 - fp, which ``exact`` reports instead, for
    k-mers seen twice. Rows with a hit form the table.
    """
    once = first_order(kmers).groupBy("kmer").agg(F.min("seq").alias("seq"), F.count("*").alias("occ"))
    flags = BlockedBloom(blocks, k).insert(once.select("seq", F.col("kmer").alias("x")))
    rows = once.join(flags, "seq").withColumn("fp", F.col("present").cast("long"))
    rows = rows.withColumn("hits", F.col("occ") - 1 + F.col("fp")).filter("hits >= 1")
    true = F.col("hits") + 1 - F.col("fp")
    rows = rows.select("kmer", "occ", "fp", "hits", (true if exact else F.col("hits") + 1).alias("n"))
    return rows.filter("n > 1") if exact else rows


def fold_masks(block: np.ndarray, mask: np.ndarray):
    """(block, one, two) of sightings: bits that at least one and at least two of them set."""
    order = np.lexsort((mask, block))
    block, mask = block[order], mask[order]
    first = np.flatnonzero(np.concatenate(([True], (block[1:] != block[:-1]) | (mask[1:] != mask[:-1]))))
    count, blocks, masks = np.diff(np.append(first, len(block))), block[first], mask[first]
    at = np.flatnonzero(np.concatenate(([True], blocks[1:] != blocks[:-1])))
    ids = blocks[at]
    one, two = np.zeros(len(at), np.int64), np.bitwise_or.reduceat(np.where(count > 1, masks, 0), at)
    size = np.diff(np.append(at, len(blocks)))
    for r in range(int(size.max())):  # the r-th distinct mask of every block; a block has few
        has = np.flatnonzero(size > r)
        m = masks[at[has] + r]
        two[has] |= one[has] & m
        one[has] |= m
    return ids, one, two


def two_level_masks(kmers: DataFrame, blocks: int, k: int) -> DataFrame:
    """block, two: bits that at least two sightings set. Tasks fold their own k-mers to masks, and only masks move."""
    bloom = BlockedBloom(blocks, k, "fast")

    def local(batches):
        held, n = [], 0
        for b in batches:
            held.append((b.column(0).to_numpy(), b.column(1).to_numpy()))
            n += b.num_rows
            if n >= CHUNK:
                yield out(held)
                held, n = [], 0
        if n:
            yield out(held)

    def out(held):
        cols = fold_masks(np.concatenate([x[0] for x in held]), np.concatenate([x[1] for x in held]))
        return pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["block", "one", "two"])

    part = kmers.select(bloom.block(F.col("kmer")).alias("block"), bloom.mask(F.col("kmer")).alias("m")).mapInArrow(local, "block long, one long, two long")
    parts = -(-blocks // SPAN)
    dealt = part.withColumn("part", F.floor(F.col("block") / SPAN).cast("int")).repartitionById(parts, "part")
    return dealt.select("block", "one", "two").mapInArrow(merge_masks, "block long, two long")


def merge_masks(batches):
    """Folds partial masks of one range of blocks in two arrays of the range's size."""
    one, two, base = np.zeros(SPAN, np.int64), np.zeros(SPAN, np.int64), None
    for b in batches:
        block, o, t = (b.column(i).to_numpy() for i in range(3))
        if not len(block):
            continue
        base = int(block[0]) // SPAN * SPAN if base is None else base
        order = np.argsort(block, kind="stable")
        at, o, t = block[order] - base, o[order], t[order]
        turn = np.arange(len(at)) - np.searchsorted(at, at)  # the r-th mask of its block in this batch
        for r in range(int(turn.max()) + 1):
            mine = turn == r
            i = at[mine]
            two[i] |= t[mine] | (one[i] & o[mine])
            one[i] |= o[mine]
    if base is not None:
        hit = np.flatnonzero(two)
        yield pa.RecordBatch.from_arrays([pa.array(hit + base), pa.array(two[hit])], names=["block", "two"])


def two_level_blocks(kmers: DataFrame, rate: float = 0.03, k: int = 4) -> int:
    """Blocks that keep the share of once-seen k-mers which pass near ``rate``, from a sketch of the distinct ones."""
    return size_for(max(1, kmers.agg(F.approx_count_distinct(F.xxhash64("kmer"), 0.02)).first()[0]), rate, k)


def count_two_level(kmers: DataFrame, blocks: int | None = None, k: int = 4, most: int = 4_000_000) -> DataFrame:
    """Exact counts of repeated k-mers: what no second sighting can have set never reaches the count's exchange.

    The filter is sized by the input. Its masks are broadcast up to ``most`` blocks (64 MB); a larger filter is joined by block,
    which moves all k-mers and so only pays where the plain count cannot hold its table.
    """
    return passing(kmers, blocks or two_level_blocks(kmers, k=k), k, most).groupBy("kmer").agg(F.count("*").alias("n")).filter("n > 1")


def passing(kmers: DataFrame, blocks: int, k: int = 4, most: int = 4_000_000) -> DataFrame:
    """Sightings whose bits at least two sightings set."""
    bloom = BlockedBloom(blocks, k, "fast")
    two = settle(two_level_masks(kmers, blocks, k))
    two = F.broadcast(two) if two.count() <= most else two
    rows = kmers.select("kmer", bloom.block(F.col("kmer")).alias("block"), bloom.mask(F.col("kmer")).alias("m"))
    return rows.join(two, "block").filter(F.col("two").bitwiseAND(F.col("m")) == F.col("m")).select("kmer")


def count_localised(kmers: DataFrame, parts: int, k: int, lanes: int = 4) -> DataFrame:
    """Baseline: every k-mer (packed, ``k`` letters) moves to its owner, which runs a filter and a table of its own.

    The owner's filter has a block for every four of its sightings. It marks bits that two sightings set, so the table gets the
    same k-mers whatever their order; those of them seen once are false positives and are dropped.
    """
    packed = kmers.select(pack_kmer(F.col("kmer")).alias("id"))
    placed = packed.withColumn("owner", F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int")).repartitionById(parts, "owner").select("id")

    def count(batches):
        held = [b.column(0).to_numpy() for b in batches]
        ids = np.concatenate(held) if held else np.zeros(0, np.int64)
        if not len(ids):
            return
        h = ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        block = ((h >> np.uint64(24)) % np.uint64(max(1, len(ids) // LOAD))).astype(np.int64)
        mask = np.zeros(len(ids), np.uint64)
        for j in range(lanes):
            mask |= np.uint64(1) << (h >> np.uint64(6 * j) & np.uint64(63))
        mask = mask.view(np.int64)
        at, _, two = fold_masks(block, mask)
        mine = two[np.searchsorted(at, block)]
        found, n = np.unique(ids[(mine & mask) == mask], return_counts=True)
        for i in range(0, len(found), CHUNK):
            some = slice(i, i + CHUNK)
            yield pa.RecordBatch.from_arrays([pa.array(found[some]), pa.array(n[some].astype(np.int64))], names=["id", "n"])

    got = placed.mapInArrow(count, "id long, n long").filter("n > 1")
    return got.select(unpack_kmer(F.col("id"), k).alias("kmer"), "n")


def filter_report(kmers: DataFrame, k: int, blocks: int) -> DataFrame:
    """What the two-level count moved and held: sightings, those that passed the filter, entries of the plain table, entries that
    passed, and bytes of the plain table, of the filter, and of the table behind it."""
    kept = passing(kmers, blocks).groupBy("kmer").agg(F.count("*").alias("n"))
    plain = kmers.groupBy("kmer").agg(F.count("*").alias("n"))

    def sums(df: DataFrame, name: str) -> DataFrame:
        return df.agg(F.sum("n").alias(f"{name}_sightings"), F.count("*").alias(f"{name}_entries"))

    both = sums(plain, "all").join(sums(kept, "kept"))  # one row each
    each = k + 8
    return both.select("all_sightings", "kept_sightings", "all_entries", "kept_entries", (F.col("all_entries") * each).alias("plain_bytes"), F.lit(8 * blocks).cast("long").alias("filter_bytes"), (F.col("kept_entries") * each).alias("table_bytes"))


def memory_report(counts: DataFrame, k: int, bits_per_key: int = 16) -> DataFrame:
    """Entries and bytes of the table with and without a filter, and bytes of the filter."""
    a = counts.agg(F.count("*").alias("all_entries"), F.sum((F.col("n") > 1).cast("long")).alias("kept_entries"))
    each = k + 8
    return a.select("all_entries", "kept_entries", (F.col("all_entries") * each).alias("plain_bytes"), (F.col("kept_entries") * each + F.floor(F.col("all_entries") * bits_per_key / 8)).cast("long").alias("filtered_bytes"))
