"""References into a partitioned address space, remote get and put with fences, bulk copies, collectives and arrays."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def ref_of(idx: Column, block_len: int) -> Column:
    return F.struct(F.floor(idx / block_len).cast("int").alias("rank"), F.pmod(idx, F.lit(block_len)).cast("long").alias("off"))


def index_of(ref: Column, block_len: int) -> Column:
    return ref["rank"].cast("long") * block_len + ref["off"]


def ref_add(ref: Column, delta, block_len: int) -> Column:
    """Moves a reference; crossing a rank boundary renormalises it."""
    return ref_of(index_of(ref, block_len) + delta, block_len)


def ref_diff(a: Column, b: Column, block_len: int) -> Column:
    return index_of(a, block_len) - index_of(b, block_len)


@dataclass(frozen=True)
class BlockArray:
    """A one-dimensional array in equal blocks over ranks. ``cells``: idx, val. Puts wait for the next fence."""

    cells: DataFrame
    length: int
    ranks: int
    version: int = 0
    pending: tuple = field(default=())

    @classmethod
    def from_df(cls, df: DataFrame, idx: str, val: str, length: int, ranks: int) -> BlockArray:
        return cls(df.select(F.col(idx).cast("long").alias("idx"), F.col(val).alias("val")), length, ranks)

    @property
    def block_len(self) -> int:
        return -(-self.length // self.ranks)

    def get(self, refs: DataFrame) -> DataFrame:
        """``refs``: seq, idx. One equi-join; cells that were put but not fenced may be missing."""
        cells = self.cells.select("idx", "val", F.lit(True).alias("_f"))
        return refs.join(cells, "idx", "left").select("seq", "idx", "val", F.coalesce("_f", F.lit(False)).alias("found"))

    def put(self, df: DataFrame) -> BlockArray:
        """``df``: seq, idx, val; only rows inside the array are taken (see :meth:`accepts`)."""
        return replace(self, pending=(*self.pending, df.select("seq", "idx", "val").filter(F.col("idx").between(0, self.length - 1))))

    def accepts(self, df: DataFrame) -> DataFrame:
        """seq, ok, reason of each row of a put: rows outside the array are refused."""
        inside = F.coalesce(F.col("idx").between(0, self.length - 1), F.lit(False))
        return df.select("seq", inside.alias("ok"), F.when(~inside, "outside").alias("reason"))

    def fence(self) -> BlockArray:
        """Applies pending puts; of several to one cell the last by seq wins. One merge."""
        if not self.pending:
            return replace(self, version=self.version + 1)
        log = self.pending[0]
        for p in self.pending[1:]:
            log = log.unionByName(p)
        last = log.groupBy("idx").agg(F.max_by("val", "seq").alias("new"), F.lit(True).alias("_p"))
        merged = self.cells.join(last, "idx", "full").select("idx", F.when(F.col("_p"), F.col("new")).otherwise(F.col("val")).alias("val"))
        return replace(self, cells=merged, version=self.version + 1, pending=())

    def slice(self, lo: int, hi: int) -> DataFrame:
        return self.cells.filter((F.col("idx") >= lo) & (F.col("idx") < hi))

    def copy_out(self, idx: int, length: int) -> DataFrame:
        """A bulk read as off, val."""
        return self.slice(idx, idx + length).select((F.col("idx") - idx).alias("off"), "val")

    def copy_in(self, idx: int, df: DataFrame, seq: int = 0) -> BlockArray:
        """A bulk write of off, val to ``idx`` and on; visible after the next fence."""
        return self.put(df.select(F.lit(seq).cast("long").alias("seq"), (F.col("off") + idx).alias("idx"), "val"))

    def local_part(self, rank: int) -> DataFrame:
        return self.slice(rank * self.block_len, (rank + 1) * self.block_len)


@dataclass(frozen=True)
class HostedArray(BlockArray):
    """An array whose cells all lie on one host."""

    host: int = 0

    @property
    def block_len(self) -> int:
        return self.length


@dataclass
class Space:
    """Ranks with segments of one size; cells are addressed by (rank, off)."""

    ranks: int
    segment_len: int
    phase: int = 0

    def array(self, df: DataFrame, idx: str, val: str) -> BlockArray:
        return BlockArray.from_df(df, idx, val, self.ranks * self.segment_len, self.ranks)

    def barrier(self) -> int:
        self.phase += 1
        return self.phase


def bcast(df: DataFrame, most_bytes: int = 64 << 20) -> DataFrame:
    """A broadcast hint, given only when the plan's own size estimate is below ``most_bytes``."""
    size = df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()
    return F.broadcast(df) if int(str(size)) <= most_bytes else df


def allreduce(df: DataFrame, aggs: dict[str, Column], onto: DataFrame) -> DataFrame:
    """Aggregates to one row that every row of ``onto`` receives."""
    return onto.crossJoin(F.broadcast(df.agg(*[c.alias(n) for n, c in aggs.items()])))
