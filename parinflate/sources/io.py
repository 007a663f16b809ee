"""Byte ranges of files, wherever they are, and listings."""

from __future__ import annotations

import hashlib
import os
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parinflate import schemas
from parinflate.runtime import ship

#: Bytes beyond a range that a block found in it may run on before the range is read anew.
LOOKAHEAD = 1 << 17


def local(path: str) -> str | None:
    if path.startswith("file:"):
        return "/" + path[5:].lstrip("/")
    return None if "://" in path else path


def read_range(path: str, offset: int, length: int) -> bytes:
    """Bytes [offset, offset + length) of a file; fewer at its end."""
    if (p := local(path)) is not None:
        with open(p, "rb") as f:
            return os.pread(f.fileno(), length, offset)
    from pyarrow.fs import FileSystem

    fs, p = FileSystem.from_uri(path)
    with fs.open_input_file(p) as f:
        return f.read_at(length, offset)


class Ranged:
    """Ranges of one file through one open handle, with ``ahead`` bytes read at a time."""

    def __init__(self, path: str, ahead: int = 4 << 20):
        self.ahead, self.base, self.held = ahead, 0, b""
        if (p := local(path)) is not None:
            self.file = open(p, "rb", buffering=0)  # noqa: SIM115
        else:
            from pyarrow.fs import FileSystem

            fs, p = FileSystem.from_uri(path)
            self.file = fs.open_input_file(p)

    def __call__(self, offset: int, length: int) -> bytes:
        """Bytes [offset, offset + length); fewer at the file's end."""
        at = offset - self.base
        if at < 0 or at + length > len(self.held):
            self.file.seek(offset)
            want, parts = max(length, self.ahead), []
            while want > 0 and (part := self.file.read(want)):
                parts.append(part)
                want -= len(part)
            self.base, self.held, at = offset, b"".join(parts), 0
        return self.held[at : at + length]

    def __enter__(self) -> Ranged:
        return self

    def __exit__(self, *_) -> None:
        self.file.close()
        self.held = b""


def read_strided(path: str, size: int, readers: int, piece: int = 128 << 10) -> list[tuple[int, bytes]]:
    """The file in pieces, each reader taking every ``readers``-th."""

    def one(k: int) -> list[tuple[int, bytes]]:
        return [(at, read_range(path, at, piece)) for at in range(k * piece, size, readers * piece)]

    with ThreadPoolExecutor(readers) as pool:
        return sorted(x for part in pool.map(one, range(readers)) for x in part)


def striped(spark: SparkSession, path: str, size: int, readers: int, piece: int = 128 << 10) -> DataFrame:
    """(at, n, md5) of a file's pieces, of which each of ``readers`` tasks reads every ``readers``-th."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in batch.column(0).to_pylist():
                with Ranged(path, piece) as read:
                    for at in range(k * piece, size, readers * piece):
                        data = read(at, piece)
                        yield pa.RecordBatch.from_pylist([{"at": at, "n": len(data), "md5": hashlib.md5(data).hexdigest()}])

    ship(spark)
    return spark.range(0, readers, 1, readers).mapInArrow(run, "at long, n long, md5 string")


def archives(spark: SparkSession, path: str) -> DataFrame:
    """(file_id, path, size) of every file below ``path``, listed by Spark; contents are not read."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("path", F.col("length").alias("size"))
    return files.select(F.abs(F.xxhash64("path")).alias("file_id"), "path", "size")


def from_rows(spark: SparkSession, rows: list[tuple[int, str]]) -> DataFrame:
    """An archive table from (file_id, local path)."""
    return spark.createDataFrame([(i, p, os.path.getsize(local(p))) for i, p in rows], schemas.ARCHIVE)
