"""Members of ZIP archives: the directory at the end by two range reads, members as raw Deflate streams from where their data begin."""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parinflate.functions.gzipfmt import ChecksumMismatch, CorruptBlock, ParinflateError
from parinflate.runtime import ship, spread
from parinflate.sources.io import Ranged

MEMBER = "path string, name string, method int, offset long, packed long, size long, crc32 long"
_END, _ENTRY, _LOCAL = b"PK\x05\x06", b"PK\x01\x02", b"PK\x03\x04"


def directory(read: Ranged, size: int) -> Iterator[tuple[str, int, int, int, int, int]]:
    """(name, method, place of the local header, packed size, size, crc) of every member."""
    tail = read(max(0, size - (1 << 16) - 22), (1 << 16) + 22)
    at = tail.rfind(_END)
    if at < 0:
        raise ParinflateError("no ZIP directory")
    n_bytes, start = struct.unpack_from("<II", tail, at + 12)
    buf, k = read(start, n_bytes), 0
    while buf[k : k + 4] == _ENTRY:
        method, crc, packed, n = struct.unpack_from("<H", buf, k + 10)[0], *struct.unpack_from("<III", buf, k + 16)
        n_name, n_extra, n_comment = struct.unpack_from("<HHH", buf, k + 28)
        place = struct.unpack_from("<I", buf, k + 42)[0]
        yield buf[k + 46 : k + 46 + n_name].decode("utf-8", "replace"), method, place, packed, n, crc
        k += 46 + n_name + n_extra + n_comment


def members(archive: DataFrame) -> DataFrame:
    """``MEMBER`` rows of every archive (file_id, path, size); ``offset`` is where a member's data begin."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = {"string": pa.string(), "int": pa.int32(), "long": pa.int64()}
        schema = pa.schema([(c.split()[0], kinds[c.split()[1]]) for c in MEMBER.split(", ")])
        for batch in batches:
            for r in batch.to_pylist():
                rows = []
                with Ranged(r["path"], 1 << 16) as read:
                    for name, method, place, packed, n, crc in list(directory(read, r["size"])):
                        head = read(place, 30)
                        if head[:4] != _LOCAL:
                            raise ParinflateError(f"no member at {place}")
                        begin = place + 30 + sum(struct.unpack_from("<HH", head, 26))
                        if not name.endswith("/"):
                            rows.append({"path": r["path"], "name": name, "method": method, "offset": begin, "packed": packed, "size": n, "crc32": crc})
                yield pa.RecordBatch.from_pylist(rows, schema=schema)

    ship(archive.sparkSession)
    return archive.mapInArrow(run, MEMBER)


def content(r: dict, step: int = 1 << 20, most: int = 8 << 20) -> Iterator[bytes]:
    """A member's bytes in parts of bounded size; its checksum is verified."""
    crc = n = 0
    d = zlib.decompressobj(-15)
    with Ranged(r["path"]) as read:
        for at in range(r["offset"], r["offset"] + r["packed"], step):
            part = read(at, min(step, r["offset"] + r["packed"] - at))
            if r["method"] == 0:
                crc, n = zlib.crc32(part, crc), n + len(part)
                yield part
                continue
            if r["method"] != 8:
                raise CorruptBlock(f"{r['name']}: method {r['method']}")
            while part:
                out = d.decompress(part, most)
                crc, n, part = zlib.crc32(out, crc), n + len(out), d.unconsumed_tail
                yield out
    if crc != r["crc32"] or n != r["size"]:
        raise ChecksumMismatch(r["name"])


def read(members_: DataFrame) -> DataFrame:
    """(path, name, off, bytes) of members, each read by a task of its own."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                off = 0
                for data in content(r):
                    if data:
                        yield pa.RecordBatch.from_arrays([pa.array([r["path"]]), pa.array([r["name"]]), pa.array([off]), pa.array([data], pa.binary())], ["path", "name", "off", "bytes"])
                    off += len(data)

    known = members_.agg(F.count(F.lit(1)), F.sum("packed")).first()
    return spread(members_, known[0], known[1] or 0).mapInArrow(run, "path string, name string, off long, bytes binary")
