"""One filter over all k-mers in the order of reads, in rounds over its blocks.

The filter's answers depend on the order of first sightings, so every distinct k-mer has to meet the earlier ones of its block.
Reads are written once in their order, two bits a letter, as rows of about a million places. A round takes a part of the
blocks: it reads all rows, and sends on k-mers of its blocks, each once a row and under six bytes long. Rows are numbered and
a row's k-mers stay in order, so no place has to move. Only one round's k-mers are on disk at a time.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from distds.functions.codecs import unpack_kmer
from distds.functions.hashing import h60_kmers
from distds.plans import stretches as st
from distds.plans.kmers import blocks_for
from distds.sources.io import forget, settle

#: Bytes of letters in a row; rounds at most; sightings of a part; letters of a k-mer at most; lanes of the filter.
CAP, ROUNDS, PART, MOST, LANES = 1 << 18, 2, 2_000_000, 21, 4


def packed(df: DataFrame, key: str, text: str, k: int) -> DataFrame:
    """read_id, n, letters of reads with a k-mer: letters become bases, four a byte, the rest goes."""

    def run(batches):
        for b in batches:
            at = 0
            for codes, ends in st.encoded(b.column(1), st.TEXT):
                begins = np.concatenate(([0], ends[:-1]))
                n = ends - begins
                size = (n + 3) // 4
                offs = np.concatenate(([0], np.cumsum(size)))
                x = np.zeros(4 * int(offs[-1]), np.uint8)
                x[np.repeat(4 * offs[:-1] - begins, n) + np.arange(len(codes))] = codes
                x = x.reshape(-1, 4)
                x = x[:, 0] << 6 | x[:, 1] << 4 | x[:, 2] << 2 | x[:, 3]
                letters = pa.BinaryArray.from_buffers(pa.binary(), len(n), [None, pa.py_buffer(offs.astype(np.int32)), pa.py_buffer(x)])
                yield pa.RecordBatch.from_arrays([b.column(0).slice(at, len(n)), pa.array(n), letters], names=["read_id", "n", "letters"])
                at += len(n)

    kind = df.schema[key].dataType.simpleString()
    return df.select(key, text).mapInArrow(run, f"read_id {kind}, n long, letters binary").filter(F.col("n") >= k)


def slices(reads: list, k: int):
    """Of reads that share an id, given as (n, letters): lists of pieces, each with the same places of all of them. Pieces overlap
    by k - 1 letters."""
    step = 4 * max(1, CAP // len(reads) - 8)
    for s in range(0, max(n for n, _ in reads) - k + 1, step):
        yield [(min(n - s, step + k - 1), x[s // 4 : (min(n, s + step + k - 1) + 3) // 4]) for n, x in reads if n - s >= k]


def rows(df: DataFrame, k: int, parts: int) -> DataFrame:
    """at, n, sizes, turns, letters: ``packed`` reads in order of their ids (null last). ``n``: k-mers; ``sizes``: letters of the
    pieces; ``turns``: pieces with the same number are one slice, whose k-mers are in order of their places."""

    def run(batches):
        base, no, held, room = TaskContext.get().partitionId() << 32, 0, [], CAP

        def row():
            sizes = np.array([n for s in held for n, _ in s], np.int32)
            turns = np.repeat(np.arange(len(held), dtype=np.int32), [len(s) for s in held])
            cols = [pa.array([base + no]), pa.array([int((sizes.astype(np.int64) - k + 1).sum())])]
            cols += [pa.array([x], pa.binary()) for x in (sizes.tobytes(), turns.tobytes(), b"".join(x for s in held for _, x in s))]
            return pa.RecordBatch.from_arrays(cols, names=["at", "n", "sizes", "turns", "letters"])

        for reads in shared(batches):
            for s in slices(reads, k):
                size = sum(len(x) for _, x in s)
                if held and size > room:
                    yield row()
                    no, held, room = no + 1, [], CAP
                held.append(s)
                room -= size
        if held:
            yield row()

    order = F.col("read_id").asc_nulls_last()
    return df.repartitionByRange(parts, order).sortWithinPartitions(order, "letters").mapInArrow(run, "at long, n long, sizes binary, turns binary, letters binary")


def shared(batches):
    """Lists of (n, letters) of reads that follow each other and share an id."""
    held, last = [], None
    for b in batches:
        for key, n, x in zip(*(b.column(i).to_pylist() for i in range(3))):
            if held and key != last:
                yield held
                held = []
            held.append((n, x))
            last = key
    if held:
        yield held


def distinct(mers: np.ndarray, k: int, times: np.ndarray | None = None):
    """(k-mers, first place, sightings: places or the sum of ``times``)."""
    bits = max(1, len(mers) - 1).bit_length()
    if 2 * k + bits <= 64:
        x = np.sort(mers << np.uint64(bits) | np.arange(len(mers), dtype=np.uint64))
        key, at = x >> np.uint64(bits), (x & np.uint64((1 << bits) - 1)).astype(np.int64)
    else:
        at = np.argsort(mers, kind="stable")
        key = mers[at]
    first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
    return key[first], at[first], np.diff(np.append(first, len(key))) if times is None else np.add.reduceat(times[at], first)


def ordered(sizes: np.ndarray, turns: np.ndarray, letters: bytes, k: int) -> np.ndarray:
    """The k-mers of a row in their order."""
    begins = (sizes + 3) // 4 * 4
    begins, n = np.cumsum(begins) - begins, sizes - k + 1
    place = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
    mers = st.rolled(st.FOUR[np.frombuffer(letters, np.uint8)].ravel(), k, np.uint64)[np.repeat(begins, n) + place]
    return mers if turns[-1] == len(turns) - 1 else mers[np.lexsort((place, np.repeat(turns, n)))]


def packet(mers: np.ndarray, times: np.ndarray) -> bytes:
    """k-mers of 42 bits and their sightings: 32 bits, 8 bits, and planes of two bits and of one that tells more than one sighting;
    these sightings follow in a byte each, or 255 and eight bytes at the end."""
    many = times[times > 1]
    planes = np.packbits([mers >> np.uint64(41) & np.uint64(1), mers >> np.uint64(40) & np.uint64(1), times > 1], axis=1)
    head = np.array([len(mers), len(many)], np.uint32)
    cols = head, mers.astype(np.uint32), (mers >> np.uint64(32)).astype(np.uint8), planes, np.minimum(many, 255).astype(np.uint8), many[many > 254]
    return b"".join(x.tobytes() for x in cols)


def unpacked(x: bytes):
    n, m = (int(i) for i in np.frombuffer(x, np.uint32, 2))
    wide, at = -(-n // 8), 8 + 5 * n
    planes = np.unpackbits(np.frombuffer(x, np.uint8, 3 * wide, at).reshape(3, wide), axis=1, count=n)
    many = np.frombuffer(x, np.uint8, m, at + 3 * wide).astype(np.int64)
    many[many == 255] = np.frombuffer(x[at + 3 * wide + m :], np.int64)
    times = np.ones(n, np.int64)
    times[planes[2] > 0] = many
    high = np.frombuffer(x, np.uint8, n, 8 + 4 * n).astype(np.uint64) | (planes[0] << 1 | planes[1]).astype(np.uint64) << np.uint64(8)
    return np.frombuffer(x, np.uint32, n, 8).astype(np.uint64) | high << np.uint64(32), times


def sent(table: DataFrame, k: int, blocks: int, parts: int, turn: int, rounds: int) -> DataFrame:
    """at, packet: k-mers that a row has in a part of the filter, in order of their first places, with their sightings. Parts are
    runs of blocks; a round has ``parts`` of them."""
    shift = np.uint64(blocks.bit_length() - 1)  # a power of two

    def run(batches):
        for b in batches:
            for at, *x in zip(*(c.to_pylist() for c in b.columns)):
                sizes, turns = (np.frombuffer(c, np.int32).astype(np.int64) for c in x[:2])
                mers = ordered(sizes, turns, x[2], k)
                key, first, n = distinct(mers, k)
                part = ((h60_kmers(key, k, 1) & np.uint64(blocks - 1)) * np.uint64(parts * rounds) >> shift).view(np.int64) - turn * parts
                mine = np.flatnonzero((part >= 0) & (part < parts))
                if not len(mine):
                    continue
                first = first[mine]
                times = np.ones(len(mers), np.int64)
                times[first] = n[mine]
                order = np.sort(part[mine] << 32 | first)
                part, first = order >> 32, order & 0xFFFFFFFF
                mers, times = mers[first], times[first]
                cuts = np.append(np.flatnonzero(np.concatenate(([True], part[1:] != part[:-1]))), len(part))
                packets = pa.array([packet(mers[i:j], times[i:j]) for i, j in zip(cuts[:-1], cuts[1:])], pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(part[cuts[:-1]].astype(np.int32)), pa.array([at] * len(packets), pa.int64()), packets], names=["part", "at", "packet"])

    out = table.select("at", "sizes", "turns", "letters").mapInArrow(run, "part int, at long, packet binary")
    return out.repartitionById(parts, "part").select("at", "packet")


def met(batches, k: int, blocks: int):
    """(k-mers, sightings, fp) of a part: fp if the bits of earlier k-mers cover those of a k-mer's first sighting."""
    held = sorted((x for b in batches for x in zip(*(c.to_pylist() for c in b.columns))), key=lambda x: x[0])
    if not held:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, bool)
    mers, times = (np.concatenate(x) for x in zip(*(unpacked(x) for _, x in held)))
    total = len(mers)
    key, first, n = distinct(mers, k, times)
    block, h, mask = h60_kmers(key, k, 1) & np.uint64(blocks - 1), h60_kmers(key, k, 2), np.zeros(len(key), np.uint64)
    for j in range(LANES):
        mask |= np.uint64(1) << (h >> np.uint64(6 * j) & np.uint64(63))
    order = np.sort(block - block.min() << np.uint64(32) | first.view(np.uint64))  # a part's blocks are fewer than 2^32
    at, order = order >> np.uint64(32), (order & np.uint64(0xFFFFFFFF)).view(np.int64)
    placed, found = np.empty(total, np.uint64), np.zeros(total, bool)
    placed[first] = mask
    mask = placed[order]
    begins = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
    size = np.diff(np.append(begins, len(at)))
    had, has = mask[begins], np.arange(len(begins))
    for r in range(1, int(size.max())):  # the r-th k-mer of every block
        has = has[size[has] > r]
        i = begins[has] + r
        new, old = mask[i], had[has]
        found[order[i]] = (old & new) == new
        had[has] = old | new
    return key, n, found[first]


def report(df: DataFrame, key: str, text: str, k: int, lead: int, rounds: int | None = None, parts: int | None = None) -> DataFrame:
    """prefix (of ``lead`` letters), kmers, fp, hits, reported, occ: ``kmers.count_bloom`` with a filter sized by the number of
    sightings, summed over the k-mers with a hit."""
    if not lead <= k <= MOST or lead > 8:
        raise ValueError(f"at most {MOST} letters, the first 8 of them to sum by")
    spark = df.sparkSession
    table = settle(rows(packed(df, key, text, k), k, st.part_count(df, text)))
    total = int(table.agg(F.sum("n")).first()[0] or 0)
    blocks = blocks_for(max(1, total))
    rounds = rounds or max(1, min(ROUNDS, -(-total // PART)))
    parts = parts or min(60_000, max(8, -(-total // (rounds * PART))))

    def run(batches):
        mers, n, fp = met(batches, k, blocks)
        by, hit = (mers >> np.uint64(2 * (k - lead))).astype(np.int64), fp | (n > 1)
        sums = [np.bincount(by[some], x, 4**lead).astype(np.int64) for some, x in ((hit, None), (fp, None), (hit, n[hit]))]
        some = np.flatnonzero(sums[0])
        yield pa.RecordBatch.from_arrays([pa.array(some), *(pa.array(x[some]) for x in sums)], names=["prefix", "kmers", "fp", "occ"])

    def summed(x: DataFrame) -> DataFrame:
        return x.groupBy("prefix").agg(*[F.sum(c).alias(c) for c in ("kmers", "fp", "occ")])

    done = None
    for turn in range(rounds):
        got = settle(summed(sent(table, k, blocks, parts, turn, rounds).mapInArrow(run, "prefix long, kmers long, fp long, occ long")))
        done = got if done is None else done.union(got)
        got.count()  # Spark's queue of events holds the plan of the last query, and so its shuffles, until another one ends
        forget(spark)  # the round's k-mers
    forget(spark, table)
    c = summed(done)
    return c.select(unpack_kmer(F.col("prefix"), lead).alias("prefix"), "kmers", "fp", (F.col("occ") - F.col("kmers") + F.col("fp")).alias("hits"), (F.col("occ") + F.col("fp")).alias("reported"), "occ")
