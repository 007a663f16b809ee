"""What the engine is compared with; each gives (bytes) so that outputs can be held against one another."""

from __future__ import annotations

import bz2
import zlib
from collections.abc import Callable, Iterator
from queue import Queue
from threading import Thread

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parinflate import schemas
from parinflate.operators import index
from parinflate.runtime import materialize, ship, spread
from parinflate.sources.gzip_source import serial
from parinflate.sources.io import Ranged, read_range

_OUT = "file_id long, seq long, bytes binary"
ZSTD_MAGIC = b"\x28\xb5\x2f\xfd"
BZIP2_BLOCK, BZIP2_END = 0x314159265359, 0x177245385090


def _per_file(archive: DataFrame, pieces: Callable[[str, int], Iterator[bytes]]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                for k, x in enumerate(pieces(r["path"], r["size"])):
                    yield pa.RecordBatch.from_arrays([pa.array([r["file_id"]]), pa.array([k]), pa.array([x], pa.binary())], ["file_id", "seq", "bytes"])

    ship(archive.sparkSession)
    return archive.mapInArrow(run, _OUT)


def builtin_gzip(spark: SparkSession, path: str) -> DataFrame:
    """B1: the codec that Spark has, one task per file; lines."""
    return spark.read.text(path)


def one_task(archive: DataFrame) -> DataFrame:
    """B2: the library's inflate, one task per file."""
    return _per_file(archive, lambda path, size: serial(path))


def helper_threads(archive: DataFrame) -> DataFrame:
    """Reading and checksums on threads of their own, inflate in between."""

    def pieces(path: str, size: int) -> Iterator[bytes]:
        raw: Queue = Queue(4)
        done: Queue = Queue(4)

        def read() -> None:
            at = 0
            while part := read_range(path, at, 4 << 20):
                at += len(part)
                raw.put(part)
            raw.put(None)

        def check() -> None:
            crc = 0
            while (x := done.get()) is not None:
                crc = zlib.crc32(x, crc)

        threads = [Thread(target=read, daemon=True), Thread(target=check, daemon=True)]
        for t in threads:
            t.start()
        d = zlib.decompressobj(31)
        while (part := raw.get()) is not None:
            while part:
                x = d.decompress(part)
                part = b""
                if d.eof:
                    part, d = d.unused_data, zlib.decompressobj(31)
                if x:
                    done.put(x)
                    yield x
        done.put(None)

    return _per_file(archive, pieces)


def text_only(spark: SparkSession, archive: DataFrame, synchronised: bool, slot_bytes: int = 32 << 20) -> DataFrame:
    """The text-only predecessor; unsynchronised output has no order, synchronised output goes through one writer."""
    from parinflate.plans.pipeline import decompress

    out = decompress(spark, archive, slot_bytes=slot_bytes, variant="text_only", mode="serial", materialize_as="symbols", ordered=False)
    return out.repartition(1).sortWithinPartitions("file_id", "out_start") if synchronised else out


def bgzf_points(archive: DataFrame, run_bytes: int = 4 << 20) -> DataFrame:
    """An index of block-gzip files by their extra fields alone: starts of runs of members, without windows or trial decoding.

    A chain from the file's start gives the members; it reads headers only.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from parinflate.functions.gzipfmt import NotGzip, parse_header

        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                at, begin, out, out_begin, no = 0, 0, 0, 0, 0
                buf, base = b"", 0
                while at < r["size"]:
                    if at + (1 << 16) + 64 > base + len(buf):
                        buf, base = read_range(r["path"], at, 8 << 20), at
                    h = parse_header(buf, at - base)
                    if h.block_bytes is None:
                        raise NotGzip("no block size in the extra field")
                    at += h.block_bytes
                    out += int.from_bytes(buf[at - base - 4 : at - base], "little")
                    if at - begin >= run_bytes or at >= r["size"]:
                        rows.append(r | {"point_no": no, "start_bit": 8 * begin, "end_bit": 8 * at if at < r["size"] else None, "kind": "member", "end_kind": "member" if at < r["size"] else None, "out_start": out_begin, "out_len": out - out_begin, "window": b""})
                        no, begin, out_begin = no + 1, at, out
            names = [c.split() for c in schemas.INDEX.split(", ")]
            kinds = {"long": pa.int64(), "string": pa.string(), "binary": pa.binary()}
            yield pa.RecordBatch.from_pylist([{n: x[n] for n, _ in names} for x in rows], schema=pa.schema([(n, kinds[k]) for n, k in names]))

    ship(archive.sparkSession)
    return archive.mapInArrow(run, schemas.INDEX)


def bgzf(archive: DataFrame) -> DataFrame:
    """Members in parallel."""
    return index.read(materialize(bgzf_points(archive), "bgzf-index"))


def _slots(archive: DataFrame, slot_bytes: int) -> DataFrame:
    from parinflate.operators.spans import plan

    return plan(archive, slot_bytes)


def zstd(archive: DataFrame, slot_bytes: int = 4 << 20, most: int = 8 << 20) -> DataFrame:
    """Frames that begin in a slot are decoded by its task, piece by piece, as far as they go. A frame's start is its magic and that it decodes; (file_id, seq, bytes), ordered by seq."""

    def frame(read: Ranged, at: int) -> Iterator[bytes | int]:
        """Pieces of the frame at byte ``at``, and at last where it ends."""
        import zstandard

        d, held, size = zstandard.ZstdDecompressor().decompressobj(), [], 0
        while part := read(at, 1 << 18):
            out = d.decompress(part)
            at += len(part) - len(d.unused_data)
            held.append(out)
            size += len(out)
            if size >= most or d.eof:
                yield b"".join(held)
                held, size = [], 0
            if d.eof:
                yield at
                return

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        for batch in batches:
            for r in batch.to_pylist():
                at, hi = r["guess_bit"] // 8, r["limit_bit"] // 8
                with Ranged(r["path"]) as read:
                    while at < hi:
                        buf = read(at, min(1 << 18, hi - at) + 3)
                        k = buf.find(ZSTD_MAGIC)
                        if k < 0:
                            at += max(1, len(buf) - 3)
                            continue
                        at, begin, seq = at + k, at + k, 0
                        try:
                            for x in frame(read, begin):
                                if isinstance(x, int):
                                    at = x
                                else:
                                    yield pa.RecordBatch.from_arrays([pa.array([r["file_id"]]), pa.array([(begin << 16) + seq]), pa.array([x], pa.binary())], ["file_id", "seq", "bytes"])
                                    seq += 1
                        except zstandard.ZstdError:
                            if seq:  # not a chance match
                                raise
                        at = max(at, begin + 1)

    ship(archive.sparkSession)
    return _dealt(archive, slot_bytes).mapInArrow(run, _OUT)


def _dealt(archive: DataFrame, slot_bytes: int) -> DataFrame:
    known = archive.agg(F.sum(F.greatest(F.lit(1), F.ceil(F.col("size") / slot_bytes))).cast("long"), F.sum("size")).first()
    return spread(_slots(archive, slot_bytes), known[0] or 0, known[1] or 0)


def bzip2_magic(buf: bytes, magic: int) -> list[int]:
    """Bit offsets of 48 bits of magic (most significant first): by its five whole bytes at each of eight shifts, then by all bits."""
    found = []
    for r in range(8):
        inner, k = (magic << (16 - r)).to_bytes(8, "big")[1:6], 0
        while (k := buf.find(inner, k + 1)) >= 0:
            at = 8 * (k - 1) + r
            if at + 48 <= 8 * len(buf) and int.from_bytes(buf[k - 1 : k + 7].ljust(8, b"\0"), "big") >> (16 - r) & (1 << 48) - 1 == magic:
                found.append(at)
    return sorted(found)


def bzip2(archive: DataFrame, slot_bytes: int = 4 << 20, look: int = 1 << 17) -> DataFrame:
    """Every block is made a stream of its own (header, its bits, end magic, its checksum) and decoded by the task of its slot. Beyond the slot, ``look`` bytes at a time are read until the last block ends."""

    def ends_of(buf: bytes) -> list[int]:
        return sorted(bzip2_magic(buf, BZIP2_BLOCK) + bzip2_magic(buf, BZIP2_END))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                lo, hi = r["guess_bit"] // 8, r["limit_bit"] // 8
                level = read_range(r["path"], 3, 1)
                buf = read_range(r["path"], lo, hi - lo + 8)
                starts = [s for s in bzip2_magic(buf, BZIP2_BLOCK) if s < 8 * (hi - lo)]
                ends = ends_of(buf)
                while starts and not (ends and ends[-1] > starts[-1]):
                    more = read_range(r["path"], lo + len(buf), look)
                    if not more:
                        break
                    at = len(buf) - 8
                    buf += more
                    ends += [x for e in ends_of(buf[at:]) if (x := 8 * at + e) not in ends]
                for s in starts:
                    e = next((x for x in ends if x > s), 8 * len(buf))
                    last = (e + 7) // 8
                    block = (int.from_bytes(buf[s // 8 : last], "big") >> (8 * last - e)) & ((1 << (e - s)) - 1)
                    check = (block >> (e - s - 80)) & 0xFFFFFFFF
                    width = e - s + 80
                    stream = ((block << 80) | (BZIP2_END << 32) | check) << (-width % 8)
                    data = bz2.decompress(b"BZh" + level + stream.to_bytes((width + 7) // 8, "big"))
                    yield pa.RecordBatch.from_arrays([pa.array([r["file_id"]]), pa.array([8 * lo + s]), pa.array([data], pa.binary())], ["file_id", "seq", "bytes"])

    ship(archive.sparkSession)
    return _dealt(archive, slot_bytes).mapInArrow(run, _OUT)


def serial_index(archive: DataFrame, spacing: int = 4 << 20) -> DataFrame:
    """An index from one pass per file, as a seekable library makes it: from each point on, the next block that is found after ``spacing`` bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                whole = r | {"start_bit": 0, "end_bit": None, "kind": "member", "end_kind": None, "out_start": 0, "window": b""}
                for no, x in enumerate(index.walk(whole, 8 * spacing)):
                    yield pa.RecordBatch.from_pylist([x | {"point_no": no}], schema=index._INDEX)

    ship(archive.sparkSession)
    return archive.mapInArrow(run, schemas.INDEX)


def total(out: DataFrame) -> int:
    return out.agg(F.sum(F.octet_length("bytes"))).first()[0] or 0
