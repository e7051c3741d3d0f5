"""k-mers that move as stretches of reads: neighbours with one minimizer travel together, two bits a letter.

The minimizer of a k-mer is its m-mer with the smallest hash, so all sightings of a k-mer go to one part, and a part gets runs
of neighbouring k-mers with the letters around them: about 1.3 bytes a sighting. A part folds its sightings in arrays, counts
behind a filter of its own, or follows the chains that stay inside it; only what crosses parts is left to join.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from distds.operators.bloom import size_for
from distds.plans.kmers import LOAD, fold_masks

#: Letters of a minimizer; sightings for a part; starts of k-mers cut at a time; k-mers of a stretch at most; sightings folded
#: at a time; bytes of stretches unpacked at a time.
M, PART, CUT, RUN, FOLD, SLAB = 9, 4_000_000, 1 << 20, 63, 4_000_000, 1 << 18
BASES = np.frombuffer(b"ACGT", np.uint8)
TEXT, SEQ = np.full(256, 4, np.uint8), np.full(256, 5, np.uint8)
for _i in range(26):
    TEXT[97 + _i] = TEXT[65 + _i] = _i % 4
SEQ[BASES] = range(4)
FOUR = np.array([[b >> 6, b >> 4 & 3, b >> 2 & 3, b & 3] for b in range(256)], np.uint8)
#: Of a set of letters (a bit each): the only one, or 4.
ONLY = np.full(16, 4, np.uint8)
ONLY[[1, 2, 4, 8]] = range(4)


def rolled(codes: np.ndarray, k: int, kind) -> np.ndarray:
    """All words of k letters, two bits each, by doubling."""
    n, at, span, out, cur = len(codes) - k + 1, 0, 1, None, codes.astype(kind)
    while k:
        if k & 1:
            piece = cur[at : at + n]
            out = piece if out is None else (out << kind(2 * span)) | piece
            at += span
        k >>= 1
        if k:
            cur = (cur[:-span] << kind(2 * span)) | cur[span:]
            span *= 2
    return out


def lowest(h: np.ndarray, w: int) -> np.ndarray:
    """The smallest of each ``w`` neighbours."""
    span = 1
    while span * 2 <= w:
        h = np.minimum(h[:-span], h[span:])
        span *= 2
    return np.minimum(h[: len(h) - (w - span)], h[w - span :]) if span < w else h


def parts_by(words: np.ndarray, k: int, m: int, parts: int) -> np.ndarray:
    """The parts of m-mers' windows: of each k-mer, given all m-mers in their order."""
    h = words * np.uint32(0x9E3779B1)
    h ^= h >> np.uint32(15)
    h = lowest(h * np.uint32(0x85EBCA6B), k - m + 1)
    h = (h ^ h >> np.uint32(13)) * np.uint32(0xC2B2AE35)
    return ((h ^ h >> np.uint32(16)) % np.uint32(parts)).astype(np.uint16)


def parts_of(kmers: np.ndarray, k: int, m: int, parts: int) -> np.ndarray:
    """The parts of packed k-mers, as :func:`parts_by` gives them to k-mers in reads."""
    low = np.uint64((1 << 2 * m) - 1)
    best = None
    for j in range(k - m + 1):
        h = (kmers >> np.uint64(2 * j) & low).astype(np.uint32) * np.uint32(0x9E3779B1)
        h ^= h >> np.uint32(15)
        h = h * np.uint32(0x85EBCA6B)
        best = h if best is None else np.minimum(best, h)
    h = (best ^ best >> np.uint32(13)) * np.uint32(0xC2B2AE35)
    return ((h ^ h >> np.uint32(16)) % np.uint32(parts)).astype(np.uint16)


def encoded(col: pa.Array, table: np.ndarray):
    """(letters, ends of the reads) of some rows at a time; letters of code 4 go, code 5 is an error."""
    col = col.cast(pa.large_binary()).fill_null(b"")
    offs = np.frombuffer(col.buffers()[1], np.int64)[col.offset : col.offset + len(col) + 1]
    data = np.frombuffer(col.buffers()[2] or b"", np.uint8)
    i = 0
    while i < len(col):
        j = max(i + 1, int(np.searchsorted(offs, offs[i] + 4 * CUT, "right")) - 1)
        codes = table[data[offs[i] : offs[j]]]
        ends = offs[i + 1 : j + 1] - offs[i]
        if len(codes) and codes.max() > 3:
            if codes.max() == 5:
                raise ValueError("reads hold A, C, G and T only")
            keep = codes < 4
            ends = np.concatenate(([0], np.cumsum(keep)))[ends]
            codes = codes[keep]
        yield codes, ends
        i = j


def cut(codes: np.ndarray, ends: np.ndarray, a: int, k: int, m: int, parts: int):
    """(part, heads, letters) of the stretches whose k-mers start in ``codes[a : a + CUT]``. A head is the number of k-mers, and
    two bits for whether a letter stands before and after; letters start at the one before, four a byte."""
    n = min(CUT, len(codes) - k + 1 - a)
    if n <= 0:
        return
    part = parts_by(rolled(codes[a : a + n + k - 1], m, np.uint32), k, m, parts)
    r0, r1 = np.searchsorted(ends, a, "right"), np.searchsorted(ends, a + n - 1, "right") + 1
    here = np.diff(np.concatenate(([a], np.minimum(ends[r0:r1], a + n))))
    end = np.repeat(ends[r0:r1], here)
    start = np.repeat(np.concatenate(([0], ends))[r0:r1], here)
    fits = np.arange(a + k, a + n + k) <= end
    same = np.zeros(n + 1, bool)
    same[1:n] = fits[1:] & fits[:-1] & (part[1:] == part[:-1]) & (start[1:] == start[:-1])
    s = np.flatnonzero(fits & ~same[:-1])
    if not len(s):
        return
    c = np.flatnonzero(fits & ~same[1:]) - s + 1
    if c.max() > RUN:
        times = -(-c // RUN)
        turn = np.arange(int(times.sum())) - np.repeat(np.cumsum(times) - times, times)
        s, c = np.repeat(s, times) + RUN * turn, np.minimum(RUN, np.repeat(c, times) - RUN * turn)
    order = np.argsort(part[s], kind="stable")
    s, c = s[order], c[order]
    heads = (c | (s + a > start[s]).astype(np.int64) << 6 | (s + c - 1 + a + k < end[s]).astype(np.int64) << 7).astype(np.uint8)
    size = (c + k + 4) // 4
    off = np.cumsum(size) - size
    at = np.repeat(s + a - 1 - 4 * off, 4 * size) + np.arange(4 * int(size.sum()))
    x = codes[np.clip(at, 0, len(codes) - 1)].reshape(-1, 4)
    letters = x[:, 0] << 6 | x[:, 1] << 4 | x[:, 2] << 2 | x[:, 3]
    mine = part[s]
    first = np.flatnonzero(np.concatenate(([True], mine[1:] != mine[:-1])))
    off = np.append(off, len(letters))
    for i, j in zip(first, np.append(first[1:], len(s))):
        yield int(mine[i]), heads[i:j].tobytes(), letters[off[i] : off[j]].tobytes()


def part_count(df: DataFrame, col: str) -> int:
    """Parts for the letters of a column, of PART sightings each."""
    return min(60_000, max(8, -(-int(df.agg(F.sum(F.length(col))).first()[0] or 0) // PART)))


def deal(df: DataFrame, col: str, k: int, parts: int, text: bool, m: int = M) -> DataFrame:
    """heads, letters of stretches in the part that their minimizer picks. ``text``: letters become bases, the rest goes;
    else ``col`` holds bases."""
    if not 2 <= k <= 29:
        raise ValueError("2 to 29 letters")
    m, table = min(m, k), TEXT if text else SEQ

    def run(batches):
        for b in batches:
            for codes, ends in encoded(b.column(0), table):
                for a in range(0, len(codes), CUT):
                    got = list(zip(*cut(codes, ends, a, k, m, parts)))
                    if got:
                        yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(got, (pa.int32(), pa.binary(), pa.binary()))], names=["part", "heads", "letters"])

    return df.select(col).mapInArrow(run, "part int, heads binary, letters binary").repartitionById(parts, "part").select("heads", "letters")


def seen(batches, k: int):
    """Sightings of a part, some at a time: k-mer, letter before and letter after (4: none), six bits for the two."""
    for b in batches:
        size = [np.frombuffer(c.buffers()[1], np.int32)[c.offset : c.offset + len(c) + 1] for c in b.columns]
        heads, letters = (np.frombuffer(c.buffers()[2] or b"", np.uint8) for c in b.columns)
        i = 0
        while i < b.num_rows:
            j = max(i + 1, int(np.searchsorted(size[1], size[1][i] + SLAB, "right")) - 1)
            h = heads[size[0][i] : size[0][j]]
            x = FOUR[letters[size[1][i] : size[1][j]]].ravel()
            c = (h & 63).astype(np.int64)
            bytes_ = (c + k + 4) // 4
            last = np.cumsum(c)
            at = np.repeat(4 * (np.cumsum(bytes_) - bytes_) + 1 - (last - c), c) + np.arange(int(last[-1]))
            left, right = x[at - 1], x[at + k]
            left[(last - c)[h & 64 == 0]] = 4
            right[(last - 1)[h & 128 == 0]] = 4
            yield rolled(x, k, np.uint64)[at] << np.uint64(6) | (left << 3 | right).astype(np.uint64)
            i = j


def folded(batches, k: int):
    """(k-mers in order, n, letters before and after as sets: five bits each, the fifth for none) of a part."""
    table, held, n = (np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.uint16)), [], 0

    def fold():
        x = np.concatenate(held)
        x.sort()
        key = x >> np.uint64(6)
        first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
        sets = np.left_shift(1, (x >> np.uint64(3) & np.uint64(7)).astype(np.uint16), dtype=np.uint16) | np.left_shift(1, (x & np.uint64(7)).astype(np.uint16) + np.uint16(5), dtype=np.uint16)
        new = key[first], np.diff(np.append(first, len(key))), np.bitwise_or.reduceat(sets, first)
        if not len(table[0]):
            return new
        key, count, sets = (np.concatenate(c) for c in zip(table, new))
        order = np.argsort(key, kind="stable")
        key = key[order]
        first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
        return key[first], np.add.reduceat(count[order], first), np.bitwise_or.reduceat(sets[order], first)

    for x in seen(batches, k):
        held.append(x)
        n += len(x)
        if n >= FOLD:
            table = fold()
            held, n = [], 0
    return fold() if held else table


def spelled(kmers: np.ndarray, k: int) -> pa.Array:
    """Packed k-mers as strings."""
    out = np.empty((len(kmers), k), np.uint8)
    for j in range(k):
        out[:, j] = BASES[(kmers >> np.uint64(2 * (k - 1 - j)) & np.uint64(3)).astype(np.uint8)]
    return fixed(out)


def fixed(letters: np.ndarray) -> pa.Array:
    n, k = letters.shape
    return pa.StringArray.from_buffers(n, pa.py_buffer((np.arange(n + 1) * k).astype(np.int32)), pa.py_buffer(np.ascontiguousarray(letters)))


def letter(codes: np.ndarray) -> pa.Array:
    """Letters of codes, null for 4."""
    return pa.array(["A", "C", "G", "T"]).take(pa.array(codes.astype(np.int8), mask=codes > 3))


def table_nodes(batches, k: int, least: int, strict: bool = False):
    """(k-mers, only letter before or 4, only letter after or 4, n) of a part's nodes."""
    key, n, sets = folded(batches, k)
    keep = n >= least
    left, right = (ONLY[sets >> s & 15] for s in (0, 5))
    if strict:
        for code, s in ((left, 0), (right, 5)):
            keep &= (sets >> s & 15 == 0) | (code < 4) & (sets >> s & 16 == 0)
    return key[keep], left[keep], right[keep], n[keep]


def nodes(dealt: DataFrame, k: int, least: int = 2, strict: bool = False) -> DataFrame:
    """kmer, left, right, n, as ``contigs.nodes`` gives them for all k-mers."""

    def run(batches):
        key, left, right, n = table_nodes(batches, k, least, strict)
        for i in range(0, len(key), CUT):
            s = slice(i, i + CUT)
            yield pa.RecordBatch.from_arrays([spelled(key[s], k), letter(left[s]), letter(right[s]), pa.array(n[s].astype(np.int64))], names=["kmer", "left", "right", "n"])

    return dealt.mapInArrow(run, "kmer string, left string, right string, n long")


class Local:
    """The graph inside a part. ``after``: the place of the next node, or -1. ``asks`` and ``offers``: nodes whose step forward
    or back leaves the part; both sides name the step by its k + 1 letters."""

    def __init__(self, batches, k: int, m: int, parts: int, least: int):
        self.key, self.left, self.right, _ = table_nodes(batches, k, least)
        key, none, top = self.key, -np.ones(len(self.key), np.int64), np.uint64(2 * (k - 1))
        self.forward = key << np.uint64(2) | self.right  # k + 1 letters
        self.back = self.left.astype(np.uint64) << np.uint64(2 * k) | key
        to = self.forward & np.uint64((1 << 2 * k) - 1)
        self.after, self.before = none, none.copy()
        if not len(key):
            self.asks = self.offers = np.zeros(0, np.int64)
            return
        at = np.minimum(np.searchsorted(key, to), len(key) - 1)
        from_ = np.flatnonzero((self.right < 4) & (key[at] == to) & (self.left[at] == key >> top))
        self.after[from_] = at[from_]
        self.before[at[from_]] = from_
        mine = parts_of(key, k, m, parts)
        open_ = np.flatnonzero((self.right < 4) & (self.after < 0))
        self.asks = open_[parts_of(to[open_], k, m, parts) != mine[open_]]
        open_ = np.flatnonzero((self.left < 4) & (self.before < 0))
        self.offers = open_[parts_of(self.back[open_] >> np.uint64(2), k, m, parts) != mine[open_]]

    def chains(self):
        """(start, place) of each node in its chain inside the part, and whether the chain is a ring."""
        n = len(self.key)
        jump, dist = np.where(self.before < 0, np.arange(n), self.before), (self.before >= 0).astype(np.int64)
        for _ in range(max(1, n).bit_length()):
            dist, jump = dist + dist[jump], jump[jump]
        ring = self.before[jump] >= 0
        for i in np.flatnonzero(ring):  # in order of k-mers, so from the smallest of its ring
            if ring[i] and jump[i] >= 0:
                at, d = i, 0
                while jump[at] >= 0:
                    jump[at], dist[at] = -1 - i, d
                    at, d = self.after[at], d + 1
        return np.where(ring, -1 - jump, jump), dist, ring


def steps(dealt: DataFrame, k: int, parts: int, m: int = M, least: int = 2) -> DataFrame:
    """kind, key: edges inside parts (0: their k + 1 letters), steps asked for (1) and offered (2) across parts, and nodes that
    no step can reach (3: their k letters)."""
    m = min(m, k)

    def run(batches):
        g = Local(batches, k, m, parts, least)
        head = g.before < 0
        head[g.offers] = False
        for kind, key in enumerate((g.forward[g.after >= 0], g.forward[g.asks], g.back[g.offers], g.key[head])):
            for i in range(0, len(key), CUT):
                some = key[i : i + CUT].view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), kind, np.int8)), pa.array(some)], names=["kind", "key"])

    return dealt.mapInArrow(run, "kind byte, key long")


def crossing(s: DataFrame) -> DataFrame:
    """key, asked, offered of steps across parts."""
    both = s.filter("kind in (1, 2)").groupBy("key").agg(F.bit_or("kind").alias("kinds"))
    return both.select("key", (F.col("kinds").bitwiseAND(F.lit(1)) > 0).alias("asked"), (F.col("kinds").bitwiseAND(F.lit(2)) > 0).alias("offered"))


def spell(df: DataFrame, col: str, k: int, cuts: dict[str, tuple[int, int]]) -> DataFrame:
    """Strings of packed words of k letters: for each name the letters from, to."""

    def run(batches):
        for b in batches:
            word = b.column(0).to_numpy().view(np.uint64)
            yield pa.RecordBatch.from_arrays([spelled(word >> np.uint64(2 * (k - j)) & np.uint64((1 << 2 * (j - i)) - 1), j - i) for i, j in cuts.values()], names=list(cuts))

    return df.select(col).mapInArrow(run, ", ".join(f"{c} string" for c in cuts))


def edges(s: DataFrame, k: int) -> DataFrame:
    """src, dst."""
    across = crossing(s).filter("asked and offered").select("key")
    return spell(s.filter("kind = 0").select("key").union(across), "key", k + 1, {"src": (0, k), "dst": (1, k + 1)})


def heads(s: DataFrame, k: int) -> DataFrame:
    """kmer: nodes that no edge reaches."""
    low = F.col("key").bitwiseAND(F.lit((1 << 2 * k) - 1))
    return spell(s.filter("kind = 3").select("key").union(crossing(s).filter("offered and not asked").select(low)), "key", k, {"kmer": (0, k)})


def fragments(dealt: DataFrame, k: int, parts: int, m: int = M, least: int = 2) -> DataFrame:
    """node (the packed first k-mer), n, letters (the last one of each node), back, forward (steps across parts, or null), ring:
    the chains inside parts. A ring inside a part starts at its smallest node."""
    m = min(m, k)

    def run(batches):
        g = Local(batches, k, m, parts, least)
        if not len(g.key):
            return
        start, place, ring = g.chains()
        order = np.lexsort((place, start))
        start = start[order]
        first = np.flatnonzero(np.concatenate(([True], start[1:] != start[:-1])))
        last = np.append(first[1:], len(order))
        goes, comes = np.zeros(len(order), bool), np.zeros(len(order), bool)
        goes[g.asks] = comes[g.offers] = True
        letters = BASES[(g.key[order] & np.uint64(3)).astype(np.uint8)]
        a, z = order[first], order[last - 1]
        for i in range(0, len(first), CUT):
            s = slice(i, i + CUT)
            offs = np.append(first[s], last[s][-1])
            text = pa.StringArray.from_buffers(len(offs) - 1, pa.py_buffer((offs - offs[0]).astype(np.int32)), pa.py_buffer(letters[offs[0] : offs[-1]].copy()))
            yield pa.RecordBatch.from_arrays([pa.array(g.key[a[s]].view(np.int64)), pa.array(last[s] - first[s]), text, pa.array(g.back[a[s]].view(np.int64), mask=~comes[a[s]]), pa.array(g.forward[z[s]].view(np.int64), mask=~goes[z[s]]), pa.array(ring[a[s]])], names=["node", "n", "letters", "back", "forward", "ring"])

    return dealt.mapInArrow(run, "node long, n long, letters string, back long, forward long, ring boolean")


def keyed(ids: np.ndarray, blocks: int, lanes: int):
    """(block, mask) of k-mers in a part's filter."""
    h = ids * np.uint64(0x9E3779B97F4A7C15)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    block = ((h >> np.uint64(24)) % np.uint64(blocks)).astype(np.int64)
    mask = np.zeros(len(ids), np.uint64)
    h *= np.uint64(0x94D049BB133111EB)
    for j in range(lanes):
        mask |= np.uint64(1) << (h >> np.uint64(40 + 6 * j) & np.uint64(63))
    return block, mask.view(np.int64)


def filtered(batches, k: int, rate: float | None = None, lanes: int = 4):
    """(k-mers that pass the part's filter, n of each, blocks, distinct k-mers or None): two levels of bits, so that a k-mer whose
    bits no second sighting can have set never reaches the table. A block for every LOAD sightings, or sized for ``rate``."""
    ids = [x >> np.uint64(6) for x in seen(batches, k)]
    ids = np.concatenate(ids) if ids else np.zeros(0, np.uint64)
    every = len(np.unique(ids)) if rate else None
    blocks = max(1, size_for(max(1, every), rate, lanes) if rate else len(ids) // LOAD)
    if not len(ids):
        return ids, np.zeros(0, np.int64), blocks, 0, 0
    block, mask = keyed(ids, blocks, lanes)
    at, _, two = fold_masks(block, mask)
    passes = (two[np.searchsorted(at, block)] & mask) == mask
    kept, n = np.unique(ids[passes], return_counts=True)
    return kept, n, blocks, every, len(ids)


def absorbed(batches, k: int, lanes: int = 4):
    """(k-mers, hits, fp) of a part: a filter absorbs the first sighting of a k-mer and the others are hits, as is the first if
    the bits of earlier k-mers cover its own (fp)."""
    ids = [x >> np.uint64(6) for x in seen(batches, k)]
    if not ids:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, bool)
    ids, first, occ = np.unique(np.concatenate(ids), return_index=True, return_counts=True)
    block, mask = keyed(ids, max(1, int(occ.sum()) // LOAD), lanes)
    order = np.lexsort((first, block))
    at, mask = block[order], mask[order]
    begins = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
    size = np.diff(np.append(begins, len(at)))
    had, fp = np.zeros(len(begins), np.int64), np.zeros(len(ids), bool)
    for r in range(int(size.max())):  # the r-th k-mer of every block
        has = np.flatnonzero(size > r)
        i = begins[has] + r
        fp[order[i]] = (had[has] & mask[i]) == mask[i]
        had[has] |= mask[i]
    return ids, occ - 1 + fp, fp


def count_absorbed(dealt: DataFrame, k: int) -> DataFrame:
    """kmer (packed), n of repeated k-mers, counted behind a filter of first sightings with its false positives taken off."""

    def run(batches):
        ids, hits, fp = absorbed(batches, k)
        n = hits + 1 - fp
        ids, n = ids[n > 1], n[n > 1]
        for i in range(0, len(ids), CUT):
            yield pa.RecordBatch.from_arrays([pa.array(ids[i : i + CUT].view(np.int64)), pa.array(n[i : i + CUT].astype(np.int64))], names=["kmer", "n"])

    return dealt.mapInArrow(run, "kmer long, n long")


def count_filtered(dealt: DataFrame, k: int) -> DataFrame:
    """kmer (packed), n of repeated k-mers, counted exactly behind filters."""

    def run(batches):
        kept, n, *_ = filtered(batches, k)
        kept, n = kept[n > 1], n[n > 1]
        for i in range(0, len(kept), CUT):
            yield pa.RecordBatch.from_arrays([pa.array(kept[i : i + CUT].view(np.int64)), pa.array(n[i : i + CUT].astype(np.int64))], names=["kmer", "n"])

    return dealt.mapInArrow(run, "kmer long, n long")


def filter_report(dealt: DataFrame, k: int, rate: float = 0.03) -> DataFrame:
    """As ``kmers.filter_report``, with a filter for each part."""

    def run(batches):
        kept, n, blocks, every, sightings = filtered(batches, k, rate)
        yield pa.RecordBatch.from_arrays([pa.array([int(x)]) for x in (sightings, n.sum(), every, len(kept), 8 * blocks)], names=["s", "ks", "e", "ke", "f"])

    a = dealt.mapInArrow(run, "s long, ks long, e long, ke long, f long").agg(*[F.sum(c).alias(c) for c in ("s", "ks", "e", "ke", "f")])
    return a.select(F.col("s").alias("all_sightings"), F.col("ks").alias("kept_sightings"), F.col("e").alias("all_entries"), F.col("ke").alias("kept_entries"), (F.col("e") * (k + 8)).alias("plain_bytes"), F.col("f").alias("filter_bytes"), (F.col("ke") * (k + 8)).alias("table_bytes"))
