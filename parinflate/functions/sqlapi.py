"""SQL functions: ``register(spark)`` makes them callable by name."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from parinflate.functions import crc, deflate_ref, gzipfmt
from parinflate.runtime import ship


def _struct(**fields: T.DataType) -> T.StructType:
    """Types as objects: a type written as text would need a session as soon as this module is imported."""
    return T.StructType([T.StructField(k, v) for k, v in fields.items()])


@pandas_udf(T.BinaryType())
def gzip_decompress(x: pd.Series) -> pd.Series:
    """All members of a small file in a cell; null for null."""
    return x.map(lambda b: None if b is None else gzipfmt.decompress(bytes(b)))


@pandas_udf(T.BinaryType())
def gzip_compress(x: pd.Series, level: pd.Series) -> pd.Series:
    from parinflate.sources.writers import gzip_member

    return pd.Series([None if b is None else gzip_member(b.encode() if isinstance(b, str) else bytes(b), int(n)) for b, n in zip(x, level, strict=True)])


@pandas_udf(T.BinaryType())
def gunzip_range(x: pd.Series, offset: pd.Series, length: pd.Series) -> pd.Series:
    return pd.Series([None if b is None else gzipfmt.decompress(bytes(b))[int(o) : int(o) + int(n)] for b, o, n in zip(x, offset, length, strict=True)])


@pandas_udf(T.LongType())
def crc32_combine(a: pd.Series, b: pd.Series, n: pd.Series) -> pd.Series:
    return pd.Series([crc.combine(int(x), int(y), int(k)) for x, y, k in zip(a, b, n, strict=True)])


@udtf(returnType=_struct(member_no=T.IntegerType(), start_byte=T.LongType(), end_byte=T.LongType(), name=T.StringType(), mtime=T.LongType(), crc32=T.LongType(), isize=T.LongType()))
class GzipMembers:
    def eval(self, data: bytes) -> Iterator[tuple]:
        for k, (h, end, _, c, n) in enumerate(gzipfmt.iter_members(bytes(data))):
            yield k, h.start, end, h.name, h.mtime, c, n


@udtf(returnType=_struct(member_no=T.IntegerType(), start_bit=T.LongType(), end_bit=T.LongType(), kind=T.StringType(), is_final=T.BooleanType(), out_len=T.LongType()))
class DeflateBlocks:
    def eval(self, data: bytes) -> Iterator[tuple]:
        buf = bytes(data)
        for k, (h, _, _, _, _) in enumerate(gzipfmt.iter_members(buf)):
            for b in deflate_ref.list_blocks(buf, 8 * h.end):
                yield k, b.start_bit, b.end_bit, b.kind, b.final, b.out_len


@udtf(returnType=_struct(line_no=T.LongType(), line=T.StringType()))
class GunzipLines:
    def eval(self, data: bytes) -> Iterator[tuple]:
        text = gzipfmt.decompress(bytes(data)).decode("utf-8", "replace")
        lines = text.split("\n")
        for k, x in enumerate(lines[:-1] if lines and not lines[-1] else lines):
            yield k, x


def is_gzip(x: Column) -> Column:
    """Whether a binary column begins like a gzip file."""
    return F.coalesce(F.hex(F.substring(x, 1, 3)) == "1F8B08", F.lit(False))


def bits_at(x: Column, bit: Column, n: int) -> Column:
    """``n`` bits (at most 17) of a binary column from ``bit``, least significant first, by built-in functions."""
    first = F.floor(bit / 8).cast("int")
    three = sum((F.coalesce(F.conv(F.hex(F.substring(x, first + k + 1, F.lit(1))), 16, 10).cast("int"), F.lit(0)) * (1 << 8 * k) for k in range(3)), F.lit(0))
    return F.floor(three / F.pow(F.lit(2), F.pmod(bit, F.lit(8)))).cast("int").bitwiseAND((1 << n) - 1)


def kraft_class(lens: Column, single_ok: bool = True) -> Column:
    """valid, over, under or empty of an array of code lengths, by built-in functions."""
    used = F.filter(lens, lambda x: x > 0)
    total = F.aggregate(used, F.lit(0).cast("long"), lambda a, x: a + F.floor(F.pow(F.lit(2.0), 15 - x)).cast("long"))
    single = (F.size(used) == 1) & (F.element_at(used, 1) == 1) if single_ok else F.lit(False)
    return F.when(F.size(used) == 0, "empty").when(total > 32768, "over").when((total == 32768) | single, "valid").otherwise("under")


def packed_add(counters: Column, symbol: Column, width: int = 5) -> Column:
    return counters + F.pow(F.lit(2.0), symbol * width).cast("long")


def register(spark: SparkSession) -> None:
    ship(spark)
    for name, f in (("gzip_decompress", gzip_decompress), ("gzip_compress", gzip_compress), ("gunzip_range", gunzip_range), ("crc32_combine", crc32_combine)):
        spark.udf.register(name, f)
    for name, f in (("gzip_members", GzipMembers), ("deflate_blocks", DeflateBlocks), ("gunzip_lines", GunzipLines)):
        spark.udtf.register(name, f)
