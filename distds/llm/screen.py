"""A screen of wanted keys, applied to rows where they lie, so that texts without a wanted key never move.

Up to ``MOST`` keys become static filters of about nine bits a key, which bounds what is sent to executors at about 34 MB.
Above that there is no screen and callers join at once. A screen lets a few unwanted keys through and never holds back a wanted
one, so an exact join always follows; results are the same either way.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from distds.llm import fuse

MOST, PART = 30_000_000, 250_000


def make_filter(table: pa.Table) -> pa.Table:
    return pa.table({"part": table.column("part").slice(0, 1), "filter": pa.array([fuse.build(table.column("key").to_numpy().view(np.uint64))], pa.binary())})


def screen(keys: DataFrame, most: int = MOST):
    """A broadcast of filters over the distinct longs ``key`` of ``keys``, or None if there are more than ``most``."""
    n = keys.count()
    if n > most:
        return None
    parts = max(1, -(-n // PART))
    part = F.pmod(F.shiftrightunsigned("key", 1), F.lit(parts)).cast("int")
    made = keys.select("key", part.alias("part")).groupBy("part").applyInArrow(make_filter, "part int, filter binary").collect()
    blobs = {r["part"]: bytes(r["filter"]) for r in made}
    empty = fuse.build(np.zeros(0, np.uint64))
    return keys.sparkSession.sparkContext.broadcast([blobs.get(i, empty) for i in range(parts)])


def maybe(blobs: list[bytes], keys: np.ndarray) -> np.ndarray:
    keys = keys.view(np.uint64)
    part = (keys >> np.uint64(1)) % np.uint64(len(blobs))
    hit = np.zeros(len(keys), dtype=bool)
    for p, blob in enumerate(blobs):
        mine = np.flatnonzero(part == p)
        hit[mine] = fuse.contains(blob, keys[mine])
    return hit


def passing(batches, blobs: list[bytes], wanted: bool = True):
    for b in batches:
        yield b.filter(pa.array(maybe(blobs, b.column("key").to_numpy()) == wanted))


def screened(df: DataFrame, filters, wanted: bool = True) -> DataFrame:
    """Rows of ``df`` (with a long ``key``) that may hold a wanted key, or with ``wanted`` false those that surely do not."""
    if filters is None:
        return df if wanted else df.limit(0)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)
    return df.mapInArrow(lambda it: passing(it, filters.value, wanted), schema)


def semi(df: DataFrame, keys: DataFrame, most: int = MOST, also: tuple[str, ...] = ()) -> DataFrame:
    """Rows of ``df`` whose ``key`` (and the columns ``also``, such as the other half of a digest) are those of ``keys``."""
    return screened(df, screen(keys.select("key").distinct(), most)).join(keys, ["key", *also], "left_semi")


def anti(df: DataFrame, keys: DataFrame, most: int = MOST, also: tuple[str, ...] = ()) -> DataFrame:
    """Rows of ``df`` whose ``key`` (and ``also``) are none of ``keys``; only rows near the keys are exchanged."""
    f = screen(keys.select("key").distinct(), most)
    return screened(df, f).join(keys, ["key", *also], "left_anti").unionByName(screened(df, f, False))
