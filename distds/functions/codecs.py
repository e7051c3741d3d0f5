"""Serialisation containers: identity adds nothing to a plan, fixed-length packs into a long, variable-length goes to a heap."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


@dataclass(frozen=True)
class Codec:
    encode: Callable[[Column], Column]
    decode: Callable[[Column], Column]
    length: str = "fixed"
    is_identity: bool = False


IDENTITY = Codec(lambda c: c, lambda c: c, is_identity=True)
_codecs: dict[str, Codec] = {}


def register_codec(data_type: T.DataType, codec: Codec) -> None:
    _codecs[data_type.simpleString()] = codec


def codec_for(data_type: T.DataType) -> Codec:
    """The codec of a type: a registered one, identity for what Spark stores natively, else JSON."""
    found = _codecs.get(data_type.simpleString())
    if found:
        return found
    if isinstance(data_type, (T.NumericType, T.BooleanType, T.StringType, T.BinaryType, T.DatetimeType, T.StructType, T.ArrayType, T.MapType)):
        return IDENTITY
    return Codec(F.to_json, lambda c: F.from_json(c, data_type), "variable")


def apply(df: DataFrame, col: str, codec: Codec, decode: bool = False) -> DataFrame:
    """Encodes or decodes a column; identity returns the very same plan."""
    if codec.is_identity:
        return df
    return df.withColumn(col, (codec.decode if decode else codec.encode)(F.col(col)))


def pack_kmer(c: Column) -> Column:
    """Two bits a letter, for up to 31 letters of ACGT."""
    return F.conv(F.translate(c, "ACGT", "0123"), 4, 10).cast("long")


def unpack_kmer(c: Column, k: int) -> Column:
    return F.translate(F.lpad(F.conv(c.cast("string"), 10, 4), k, "0"), "0123", "ACGT")


def kmer_codec(k: int) -> Codec:
    if not 1 <= k <= 31:
        raise ValueError("1 to 31 letters")
    return Codec(pack_kmer, lambda c: unpack_kmer(c, k))


def pack_pair(a: Column, b: Column) -> Column:
    """Two ints in a long."""
    return F.shiftleft(a.cast("long"), 32).bitwiseOR(b.cast("long").bitwiseAND(F.lit(0xFFFFFFFF)))


def unpack_pair(c: Column) -> Column:
    return F.struct(F.shiftright(c, 32).cast("int").alias("a"), c.bitwiseAND(F.lit(0xFFFFFFFF)).cast("int").alias("b"))


class Heap:
    """Variable-length values kept apart: rows carry a pointer, and payloads are joined in only when asked for."""

    def __init__(self, df: DataFrame, key: str, col: str, block_len: int):
        ref = F.struct(F.floor(F.col(key) / block_len).cast("int").alias("rank"), F.pmod(F.col(key), F.lit(block_len)).cast("long").alias("off"))
        self.rows = df.withColumn("ref", ref).drop(col)
        self.payload = df.select(ref.alias("ref"), F.to_binary(F.col(col), F.lit("utf-8")).alias("bytes"))

    def fetch(self, rows: DataFrame, out: str) -> DataFrame:
        return rows.join(self.payload, "ref", "left").withColumn(out, F.col("bytes").cast("string")).drop("bytes")
