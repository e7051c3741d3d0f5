"""Word and shingle hashes of whole texts, computed for many documents at once with numpy."""

from __future__ import annotations

import hashlib

import numpy as np


#: Texts are hashed in runs of about this many bytes, which bounds memory whatever the batch.
RUN_BYTES = 1 << 18

M1, M2, GOLD = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB), np.uint64(0x9E3779B97F4A7C15)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit words."""
    x = (x ^ (x >> np.uint64(30))) * M1
    x = (x ^ (x >> np.uint64(27))) * M2
    return x ^ (x >> np.uint64(31))


BYTE_CODES = mix64(np.arange(1, 257, dtype=np.uint64) * GOLD)
STEP = np.uint64(0x9E6C63D0676A9A99)
SPACE = np.zeros(256, dtype=bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32


def runs_of(texts, limit: int = RUN_BYTES):
    """Yields (first index, list of bytes) with about ``limit`` bytes each; ``texts``: a pyarrow string array."""
    run, size, first = [], 0, 0
    for i, t in enumerate(texts):
        b = (t.as_py() or "").encode("utf-8", "surrogatepass") if t.is_valid else b""
        if run and size + len(b) > limit:
            yield first, run
            run, size, first = [], 0, i
        run.append(b)
        size += len(b)
    if run:
        yield first, run


def words(run: list[bytes], fold: bool = True):
    """(bytes of all texts, word starts, word ends, words before each text): words are runs of non-white-space bytes."""
    data = np.frombuffer(b" ".join(run) + b" ", dtype=np.uint8)
    if fold:
        data = FOLD[data]
    gap = SPACE[data]
    edge = np.diff(np.concatenate(([True], gap)).astype(np.int8))
    starts, ends = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
    offsets = np.cumsum([0] + [len(b) + 1 for b in run])
    return data, starts, ends, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    if not len(starts):
        return np.zeros(0, np.uint64)
    n = ends - starts
    powers = np.cumprod(np.full(int(n.max()), STEP, dtype=np.uint64))
    first = np.concatenate(([0], np.cumsum(n)[:-1]))
    inside = np.arange(int(n.sum())) - np.repeat(first, n)
    values = BYTE_CODES[data[np.repeat(starts, n) + inside]] * powers[inside]
    return mix64(np.add.reduceat(values, first) + n.astype(np.uint64) * GOLD)


def shingle_hashes(w: np.ndarray, k: int) -> np.ndarray:
    """Hashes of the k-word shingles of one text; with fewer words the whole sequence is one."""
    if not len(w):
        return w
    m = min(k, len(w))
    out = np.full(len(w) - m + 1, np.uint64(m), dtype=np.uint64)
    for j in range(m):
        out = mix64(out * STEP + w[j : len(w) - m + 1 + j])
    return out


def shingle_sets(run: list[bytes], k: int):
    """The sorted set of shingle hashes of each text."""
    data, starts, ends, cuts = words(run)
    h = word_hashes(data, starts, ends)
    for i in range(len(run)):
        s = np.sort(shingle_hashes(h[cuts[i] : cuts[i + 1]], k))
        yield s[np.concatenate(([True], s[1:] != s[:-1]))] if len(s) else s


def digest(s: np.ndarray) -> tuple[int, int]:
    """A 128-bit digest of a set, as two signed longs."""
    d = hashlib.blake2b(s.tobytes(), digest_size=16).digest()
    return int.from_bytes(d[:8], "little", signed=True), int.from_bytes(d[8:], "little", signed=True)
