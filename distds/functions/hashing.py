"""Hashes: a portable one that SQL engines agree on, and Spark's fast one."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def h60(c: Column, seed: int = 0) -> Column:
    """60 bits of md5 as a long; equal in every engine with md5."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}#"), c.cast("string"))), 1, 15), 16, 10).cast("long")


def fast(c: Column, seed: int = 0) -> Column:
    """Spark's 64-bit hash without the sign bit; same logical results as :func:`h60`, other slots."""
    return F.xxhash64(c, F.lit(seed)).bitwiseAND(F.lit((1 << 60) - 1))


HASHES = {"portable": h60, "fast": fast}


def h60_sql(expr: str, seed: int = 0) -> str:
    """The portable hash in DuckDB SQL, for oracles."""
    return f"('0x' || substr(md5('{seed}#' || CAST({expr} AS VARCHAR)), 1, 15))::BIGINT"


def owner(slot: Column, capacity: int, ranks: int) -> Column:
    """The rank that owns a slot of a table in blocks."""
    return F.floor(slot / F.lit(-(-capacity // ranks))).cast("int")


#: Sines and turns of md5, and hashes at a time: few enough for the cache.
SINES, TURNS, AT_ONCE = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)], [(7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)], 1 << 15
#: Four letters, two bits each, as a word of md5.
FOUR_LETTERS = np.array([int.from_bytes(bytes(b"ACGT"[i >> s & 3] for s in (6, 4, 2, 0)), "little") for i in range(256)], np.uint32)


def h60_kmers(kmers: np.ndarray, k: int, seed: int = 0) -> np.ndarray:
    """:func:`h60` of packed words of ``k`` letters, as unsigned longs."""
    head = f"{seed}#".encode()
    if not 0 < len(head) + k < 56:
        raise ValueError("the text has to fit one block of md5")
    out = np.empty(len(kmers), np.uint64)
    for i in range(0, len(kmers), AT_ONCE):
        out[i : i + AT_ONCE] = _h60_block(kmers[i : i + AT_ONCE], k, head)
    return out


def _words(kmers: np.ndarray, k: int, head: bytes) -> list:
    """The sixteen words of a text's block; words without letters are numbers."""
    fixed = bytearray(64)
    fixed[: len(head)] = head
    fixed[len(head) + k] = 0x80
    fixed[56:64] = (8 * (len(head) + k)).to_bytes(8, "little")
    out = []
    for j in range(16):
        at = [4 * j + c - len(head) for c in range(4)]  # letters of the word
        if at[0] >= 0 and at[3] < k:
            out.append(FOUR_LETTERS[(kmers >> np.uint64(2 * (k - 1 - at[3])) & np.uint64(255)).astype(np.uint8)])
            continue
        word = int.from_bytes(fixed[4 * j : 4 * j + 4], "little")
        for c, i in enumerate(at):
            if 0 <= i < k:
                word = word | (FOUR_LETTERS[(kmers >> np.uint64(2 * (k - 1 - i)) & np.uint64(3)).astype(np.uint8)] >> np.uint32(24)) << np.uint32(8 * c)
        out.append(word)
    return out


def _h60_block(kmers: np.ndarray, k: int, head: bytes) -> np.ndarray:
    words, n = _words(kmers, k, head), len(kmers)
    start = [np.uint32(x) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]
    a, b, c, d = (np.full(n, x, np.uint32) for x in start)
    f, g = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        kind = i // 16
        if kind < 2:  # one of two words picks bits of the others
            x, y, z = (b, c, d) if kind == 0 else (d, b, c)
            np.bitwise_xor(y, z, out=f)
            np.bitwise_and(f, x, out=f)
            np.bitwise_xor(f, z, out=f)
        elif kind == 2:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
        else:
            np.invert(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
        w = words[(i, 5 * i + 1, 3 * i + 5, 7 * i)[kind] % 16]
        f += a
        if isinstance(w, np.ndarray):
            f += w
            w = 0
        f += np.uint32((SINES[i] + w) & 0xFFFFFFFF)
        turn = TURNS[kind][i % 4]
        np.right_shift(f, np.uint32(32 - turn), out=g)
        np.left_shift(f, np.uint32(turn), out=f)
        f |= g
        f += b
        a, b, c, d, f = d, f, b, c, a
    high, low = ((x + s).byteswap().astype(np.uint64) for x, s in ((a, start[0]), (b, start[1])))
    return (high << np.uint64(32) | low) >> np.uint64(4)
