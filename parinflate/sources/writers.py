"""Compressed files of many layouts, written by executors: slices are compressed in parallel, one task appends them in order."""

from __future__ import annotations

import bz2
import heapq
import os
import struct
import tarfile
import tempfile
import zlib
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parinflate.functions import crc as crc_
from parinflate.runtime import FAT_ROWS, materialize, ship, spread
from parinflate.sources.io import local

HEADER = b"\x1f\x8b\x08\0\0\0\0\0\0\xff"
BGZF_BLOCK = 65280
SLICE = "part long, data binary, before binary"
STRATEGIES = {"default": zlib.Z_DEFAULT_STRATEGY, "filtered": zlib.Z_FILTERED, "huffman_only": zlib.Z_HUFFMAN_ONLY, "rle": zlib.Z_RLE, "fixed_only": zlib.Z_FIXED}
LAYOUTS = ("single", "pigz_like", "multi_member", "bgzf", "stored_only", "fixed_only", "huffman_only", "rle", "sync_flush_dense", "single_dynamic_block", "nested", "zlib", "raw", "zstd_frames", "zstd_frames_unchecked", "zstd_single", "zstd_single_unchecked", "bzip2_streams", "raw_copy")


def gzip_member(data: bytes, level: int = 6, strategy: str = "default", mem_level: int = 8, extra: bytes = b"") -> bytes:
    c = zlib.compressobj(level, zlib.DEFLATED, -15, mem_level, STRATEGIES[strategy])
    head = HEADER if not extra else HEADER[:3] + b"\x04" + HEADER[4:] + struct.pack("<H", len(extra)) + extra
    return head + c.compress(data) + c.flush() + struct.pack("<II", zlib.crc32(data), len(data) & 0xFFFFFFFF)


def bgzf(data: bytes, level: int = 6, end: bool = False) -> bytes:
    """Block-gzip members; the extra field holds a member's size less one."""
    out = []
    for at in range(0, len(data), BGZF_BLOCK):
        m = gzip_member(data[at : at + BGZF_BLOCK], level, extra=b"BC\x02\0\0\0")
        out.append(m[:16] + struct.pack("<H", len(m) - 1) + m[18:])
    if end:
        m = gzip_member(b"", 6, extra=b"BC\x02\0\0\0")
        out.append(m[:16] + struct.pack("<H", len(m) - 1) + m[18:])
    return b"".join(out)


def code_lengths(counts: dict[int, int], most: int = 15) -> dict[int, int]:
    """Lengths of a complete prefix code: Huffman's, flattened by halving counts until none is longer than ``most``."""
    if len(counts) == 1:
        return {s: 1 for s in counts}
    while True:
        heap = [(n, s, {s: 0}) for s, n in counts.items()]
        heapq.heapify(heap)
        while len(heap) > 1:
            a, s, x = heapq.heappop(heap)
            b, _, y = heapq.heappop(heap)
            heapq.heappush(heap, (a + b, s, {k: v + 1 for k, v in (x | y).items()}))
        lens = heap[0][2]
        if max(lens.values()) <= most:
            return lens
        counts = {s: (n + 1) // 2 for s, n in counts.items()}


def single_dynamic_block(data: bytes) -> bytes:
    """A member of one dynamic block of literals only: nothing for a finder to find."""
    return b"".join(dynamic_block([data], np.bincount(np.frombuffer(data, np.uint8), minlength=256), zlib.crc32(data)))


def dynamic_block(parts: Iterable[bytes], counts: np.ndarray, crc: int) -> Iterator[bytes]:
    """The same piece by piece, from parts of the data that together have ``counts`` of each byte and the checksum ``crc``."""
    lens = code_lengths({s: int(n) for s, n in enumerate(counts) if n} | {256: 1})
    code, codes = 0, np.zeros(257, np.int64)
    width = np.zeros(257, np.int64)
    for n in range(1, 16):
        for s in sorted(k for k, v in lens.items() if v == n):
            codes[s], width[s] = int(format(code, f"0{n}b")[::-1], 2), n
            code += 1
        code <<= 1
    # Sixteen precode symbols of four bits each; no repeats.
    fields = [(1, 1), (2, 2), (0, 5), (0, 5), (15, 4)] + [(4 if s < 16 else 0, 3) for s in (16, 17, 18, 0, 8, 7, 9, 6, 10, 5, 11, 4, 12, 3, 13, 2, 14, 1, 15)]
    fields += [(int(format(int(width[s]), "04b")[::-1], 2), 4) for s in range(257)] + [(0, 4)]
    rest = np.array([(v >> k) & 1 for v, w in fields for k in range(w)], np.uint8)
    yield HEADER

    def packed(syms: np.ndarray, before: np.ndarray) -> np.ndarray:
        n = width[syms]
        at = np.cumsum(n) - n + len(before)
        bits = np.zeros(int(n.sum()) + len(before), np.uint8)
        bits[: len(before)] = before
        c = codes[syms]
        for k in range(15):
            on = n > k
            bits[at[on] + k] = (c[on] >> k) & 1
        return bits

    for part in parts:
        for lo in range(0, len(part), 1 << 20):
            bits = packed(np.frombuffer(part[lo : lo + (1 << 20)], np.uint8).astype(np.int64), rest)
            whole = len(bits) // 8 * 8
            yield np.packbits(bits[:whole], bitorder="little").tobytes()
            rest = bits[whole:]
    yield np.packbits(packed(np.array([256]), rest), bitorder="little").tobytes() + struct.pack("<II", crc, int(counts.sum()) & 0xFFFFFFFF)


def slices(lines: DataFrame, order: list[str], line: str = "line", parts: int | None = None, slice_bytes: int = 1 << 20, newline: bytes = b"\n") -> DataFrame:
    """(part, data, before): lines in order, each with its newline, as slices of about ``slice_bytes``; ``part`` orders them.

    ``before`` is the last 32 KiB before a slice, for layouts that carry a history on; a task's first slice has none.
    """
    ship(lines.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, held, size, before = TaskContext.get().partitionId() << 32, [], 0, b""

        def out(data: bytes) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([part]), pa.array([data], pa.binary()), pa.array([before], pa.binary())], ["part", "data", "before"])

        for batch in batches:
            for x in batch.column(0).to_pylist():
                held.append(x + newline)
                size += len(x) + len(newline)
                if size >= slice_bytes:
                    data = b"".join(held)
                    yield out(data)
                    part, held, size, before = part + 1, [], 0, data[-32768:]
        if held:
            yield out(b"".join(held))

    ranged = lines.repartitionByRange(parts or max(8, lines.sparkSession.sparkContext.defaultParallelism), *order).sortWithinPartitions(*order)
    return ranged.select(F.col(line).cast("binary").alias("line")).mapInArrow(run, SLICE)


def slices_by(lines: DataFrame, path: str, order: list[str], line: str = "line", slice_bytes: int = 1 << 18) -> DataFrame:
    """(path, part, data): for each value of column ``path`` its lines in order, each with its newline, as slices of about ``slice_bytes``."""
    ship(lines.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, part, held, size = None, TaskContext.get().partitionId() << 32, [], 0

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([now]), pa.array([part]), pa.array([b"".join(held)], pa.binary())], ["path", "part", "data"])

        for batch in batches:
            for p, x in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if held and (p != now or size >= slice_bytes):
                    yield out()
                    part, held, size = part + 1, [], 0
                now = p
                held.append(x + b"\n")
                size += len(x) + 1
        if held:
            yield out()

    ranged = lines.repartitionByRange(max(8, lines.sparkSession.sparkContext.defaultParallelism), path, *order).sortWithinPartitions(path, *order)
    return ranged.select(path, F.col(line).cast("binary").alias("line")).mapInArrow(run, "path string, part long, data binary")


def _compress(layout: str, level: int) -> Callable:
    """One slice to (path, part, n, crc, bytes); ``before`` is the end of the slice before it, for layouts that carry it on."""

    def one(data: bytes, before: bytes) -> bytes:
        if layout == "pigz_like":
            c = zlib.compressobj(level, zlib.DEFLATED, -15, 8, zlib.Z_DEFAULT_STRATEGY, before) if before else zlib.compressobj(level, zlib.DEFLATED, -15)
            return c.compress(data) + c.flush(zlib.Z_SYNC_FLUSH)
        if layout == "multi_member":
            return gzip_member(data, level)
        if layout == "bgzf":
            return bgzf(data, level)
        if layout.startswith("zstd_frames"):
            import zstandard

            return zstandard.ZstdCompressor(level=3, write_content_size=True, write_checksum=layout == "zstd_frames").compress(data)
        if layout == "bzip2_streams":
            return bz2.compress(data, min(9, max(1, level)))
        return data

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                yield pa.RecordBatch.from_arrays([pa.array([r["path"]]), pa.array([r["part"]]), pa.array([len(r["data"])]), pa.array([zlib.crc32(r["data"])]), pa.array([one(r["data"], r["before"] or b"")], pa.binary())], ["path", "part", "n", "crc", "bytes"])

    return run


class _File:
    """One file being written, slice by slice; no more than a slice is held. A block of one code, which all bytes decide, waits for them in a temporary file of the task."""

    def __init__(self, path: str, layout: str, level: int):
        self.path, self.layout, self.level, self.out = path, layout, level, open_out(path)
        self.crc = self.n = 0
        if layout == "single_dynamic_block":
            self.held, self.counts = tempfile.TemporaryFile(), np.zeros(256, np.int64)  # noqa: SIM115
        if layout == "nested":
            self.inner = zlib.compressobj(level, zlib.DEFLATED, 31)
            level = 0
        wbits = {"zlib": 15, "raw": -15}.get(layout, 31)
        self.stream = zlib.compressobj(0 if layout == "stored_only" else level, zlib.DEFLATED, wbits, 8, STRATEGIES[layout if layout in STRATEGIES else "default"])
        if layout == "pigz_like":
            self.out.write(HEADER)
        if layout.startswith("zstd_single"):
            import zstandard

            self.stream = zstandard.ZstdCompressor(level=3, write_checksum=layout != "zstd_single_unchecked").compressobj()

    def add(self, data: bytes, n: int, crc: int) -> None:
        """A slice as :func:`_compress` left it, of ``n`` bytes with checksum ``crc``."""
        if self.layout in CUT:
            self.out.write(data)
        elif self.layout == "single_dynamic_block":
            self.held.write(data)
            self.counts += np.bincount(np.frombuffer(data, np.uint8), minlength=256)
        elif self.layout == "nested":
            self.out.write(self.stream.compress(self.inner.compress(data)))
        elif self.layout == "sync_flush_dense":
            for k in range(0, len(data), 4096):
                self.out.write(self.stream.compress(data[k : k + 4096]) + self.stream.flush(zlib.Z_SYNC_FLUSH))
        else:
            self.out.write(self.stream.compress(data))
        self.crc, self.n = crc_.combine(self.crc, crc, n), self.n + n

    def close(self) -> int:
        if self.layout == "pigz_like":
            self.out.write(b"\x03\0" + struct.pack("<II", self.crc, self.n & 0xFFFFFFFF))
        elif self.layout == "bgzf":
            self.out.write(bgzf(b"", end=True))
        elif self.layout == "single_dynamic_block":
            self.held.seek(0)
            for data in dynamic_block(iter(lambda: self.held.read(1 << 20), b""), self.counts, self.crc):
                self.out.write(data)
            self.held.close()
        elif self.layout == "nested":
            self.out.write(self.stream.compress(self.inner.flush()) + self.stream.flush())
        elif self.layout not in CUT:
            self.out.write(self.stream.flush())
        self.out.close()
        return self.n


#: Layouts whose slices are compressed by themselves.
CUT = ("pigz_like", "multi_member", "bgzf", "zstd_frames", "zstd_frames_unchecked", "bzip2_streams", "raw_copy")


def _append(layout: str, level: int) -> Callable:
    """Rows (path, part, n, crc, bytes) sorted by path and part: each path becomes a file."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now: _File | None = None
        for batch in batches:
            for k in range(batch.num_rows):
                r = batch.slice(k, 1).to_pylist()[0]
                if now is None or now.path != r["path"]:
                    if now is not None:
                        yield pa.RecordBatch.from_arrays([pa.array([now.path]), pa.array([now.close()])], ["path", "n"])
                    now = _File(r["path"], layout, level)
                now.add(r["bytes"], r["n"], r["crc"])
        if now is not None:
            yield pa.RecordBatch.from_arrays([pa.array([now.path]), pa.array([now.close()])], ["path", "n"])

    return run


def open_out(path: str):
    """A file to write, made complete only when it is closed: it is written beside its place and moved there."""
    p = local(path)
    if p is None:
        from pyarrow.fs import FileSystem

        fs, q = FileSystem.from_uri(path)
        return fs.open_output_stream(q)
    os.makedirs(os.path.dirname(p), exist_ok=True)
    f = open(f"{p}.{os.getpid()}.part", "wb")  # noqa: SIM115
    close = f.close

    def done() -> None:
        close()
        os.replace(f.name, p)

    f.close = done
    return f


def write(parts: DataFrame, path: str, layout: str = "single", level: int = 6) -> int:
    """Write slices as one file; bytes in. A file is one object, so its writer is one task; compression before it is parallel where the layout lets it be."""
    rows = write_files(parts.withColumn("path", F.lit(path)), layout, level, 1)
    return rows[0][1] if rows else _File(path, layout, level).close()  # nothing in it


def write_files(parts: DataFrame, layout: str = "single", level: int = 6, files: int | None = None) -> list[tuple[str, int]]:
    """Write slices (path, part, data, before) as one file per path; (path, bytes in) of each. Files are written side by side, by a task each."""
    spark = parts.sparkSession
    parts = materialize(parts if "before" in parts.columns else parts.withColumn("before", F.lit(None).cast("binary")), "slices", "lz4", FAT_ROWS)
    paths = parts.select("path").distinct().count() if files is None else files
    small = spread(parts, parts.count(), 0) if layout in CUT else parts
    small = small.mapInArrow(_compress(layout, level), "path string, part long, n long, crc long, bytes binary")
    by_path = small.repartition(1) if paths <= 1 else small.repartition(min(paths, max(1, 4 * spark.sparkContext.defaultParallelism)), "path")
    return [(r.path, r.n) for r in by_path.sortWithinPartitions("path", "part").mapInArrow(_append(layout, level), "path string, n long").collect()]


def tar_header(name: str, size: int) -> bytes:
    info = tarfile.TarInfo(name)
    info.size = size
    return info.tobuf(tarfile.USTAR_FORMAT)


def tar_slices(spark, members: list[tuple[str, DataFrame]]) -> DataFrame:
    """Slices of an archive of named members, each given as slices; only names and sizes reach the driver."""
    out = None
    for no, (name, parts) in enumerate(members):
        parts = materialize(parts, "member", "lz4", FAT_ROWS)
        size = parts.agg(F.sum(F.octet_length("data").cast("long"))).first()[0] or 0
        ends = [(no << 56, tar_header(name, size)), ((no << 56) + (1 << 55), b"\0" * (-size % 512) + (b"\0" * 1024 if no == len(members) - 1 else b""))]
        whole = parts.select((F.col("part") + (no << 56) + 1).alias("part"), "data").union(spark.createDataFrame(ends, "part long, data binary"))
        out = whole if out is None else out.union(whole)
    return out.withColumn("before", F.lit(None).cast("binary"))
