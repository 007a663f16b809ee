"""``spark.read.format("parinflate")`` and ``df.write.format("parinflate")``.

Reading, options: ``index``, a saved index, whose row groups are read side by side; without one, ``path`` is a file or a folder, of which
each file is read by one task. ``format``: bytes (file_id, point_no, out_start,
bytes), lines (file_id, out_pos, line), or csv and json with a schema. A line belongs to the partition in which it begins; to end it,
the next row groups are read on. ``onError`` fail or skip (a damaged file without index gives what comes before the damage). ``upto``:
only what lies before that byte of each file. ``variant`` text_only refuses bytes outside 9 to 126. With ``pushdown`` true
(and spark.sql.python.filterPushdown.enabled) filters on file_id, point_no and out_start that compare with constants leave
only the row groups and points that can satisfy them.

Writing: one column of lines (string or binary); each task writes one file. Options: ``layout`` single, bgzf or multi_member; ``level``.
"""

from __future__ import annotations

import csv
import io as io_
import json
import os
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import pyarrow.dataset as ds
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual, WriterCommitMessage
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from parinflate import schemas
from parinflate.functions.gzipfmt import NonTextByte, ParinflateError
from parinflate.operators.index import point_bytes
from parinflate.sources.io import Ranged, local
from parinflate.sources.reader import META

_COMPARE = {EqualTo: "=", GreaterThan: ">", GreaterThanOrEqual: ">=", LessThan: "<", LessThanOrEqual: "<="}
#: Row groups after its own in which a partition looks for the end of its last line; lines of a batch.
AHEAD, BATCH = 16, 10_000
LINES = "file_id long, out_pos long, line string"


@dataclass
class Groups(InputPartition):
    """A row group of an index, as (file, number), and those after it."""

    own: tuple[str, int]
    after: list[tuple[str, int]]


@dataclass
class Whole(InputPartition):
    """A file."""

    file_id: int
    path: str


def _overlaps(limits: list[tuple[str, str, int]], of: dict[str, tuple[int, int]]) -> bool:
    for col, op, v in limits:
        lo, hi = of[col]
        if op == "=" and not lo <= v <= hi or op == ">" and hi <= v or op == ">=" and hi < v or op == "<" and lo >= v or op == "<=" and lo > v:
            return False
    return True


class _Plain(DataSourceReader):
    def __init__(self, options, schema: StructType):
        self.path, self.index, self.format = options.get("path"), options.get("index"), options.get("format", "bytes")
        self.on_error, self.variant, self.upto = options.get("onError", "fail"), options.get("variant", "general"), options.get("upto")
        self.schema = schema
        self.limits: list[tuple[str, str, int]] = [("out_start", "<", int(self.upto))] if self.upto and self.index else []

    # planning

    def partitions(self) -> list[InputPartition]:
        if not self.index:
            return [Whole(k, path) for k, path in enumerate(_files(self.path))]
        found = []
        for f in ds.dataset(local(self.index) or self.index, partitioning=None).get_fragments():
            for g in f.row_groups:
                stats = {c: (s["min"], s["max"]) for c, s in (g.statistics or {}).items() if c in META and s}
                found.append((stats["file_id"][0], stats["out_start"][0], stats, (f.path, g.id)))
        found.sort(key=lambda x: x[:2])
        refs = [x[3] for x in found]
        out = []
        for k, (_, _, stats, ref) in enumerate(found):
            # Bytes of a point reach beyond the least and largest start, so only the lower side of its range is certain.
            of = {c: stats[c] for c in ("file_id", "point_no")} | {"out_start": (stats["out_start"][0], stats["out_start"][1] + stats["out_len"][1])}
            if _overlaps(self.limits, of):
                out.append(Groups(ref, refs[k + 1 : k + 1 + AHEAD]))
        return out

    # reading

    def _points(self, ref: tuple[str, int]) -> Iterator[dict]:
        fragment = ds.ParquetFileFormat().make_fragment(*_place(ref[0]), row_groups=[ref[1]])
        yield from (r for b in fragment.to_batches(batch_size=16) for r in b.to_pylist())

    def _checked(self, pieces: Iterator[bytes]) -> Iterator[bytes]:
        odd = bytes(range(9)) + bytes(range(127, 256))
        for data in pieces:
            if self.variant == "text_only" and len(data.translate(None, odd)) < len(data):
                raise NonTextByte("a byte outside 9 to 126")
            yield data

    def _may(self, r: dict) -> bool:
        return _overlaps(self.limits, {"file_id": (r["file_id"],) * 2, "point_no": (r["point_no"],) * 2, "out_start": (r["out_start"], r["out_start"] + max(1, r["out_len"]) - 1)})

    def _pieces(self, p: Groups | Whole) -> Iterator[tuple[int, int, int, bytes, bool]]:
        """(file_id, point_no, out_start, bytes, own): what a partition holds and, for lines, what comes after it."""
        if isinstance(p, Whole):
            at = 0
            try:
                for data in self._checked(members(p.path)):
                    data = data[: int(self.upto) - at] if self.upto else data
                    if not data:
                        return
                    yield p.file_id, 0, at, data, True
                    at += len(data)
            except (zlib.error, ParinflateError):
                if self.on_error == "fail":
                    raise
            return
        for k, ref in enumerate([p.own, *(p.after if self.format != "bytes" else [])]):
            for r in self._points(ref):
                if k or self._may(r):
                    at = r["out_start"]
                    for data in self._checked(point_bytes(r)):
                        if self.upto:
                            data = data[: max(0, int(self.upto) - at)]
                        yield r["file_id"], r["point_no"], at, data, not k
                        at += len(data)

    def _lines(self, p: Groups | Whole) -> Iterator[tuple[int, int, bytes]]:
        """(file_id, out_pos, line) of a partition: of lines that begin in it but for the first, and of the one that ends after it or begins right there."""
        file_id, at, rest, skip, inside = None, 0, b"", False, True
        for f, _, start, data, inside in self._pieces(p):
            if f != file_id:  # a file ends, and its last line
                if file_id is not None and rest and not skip:
                    yield file_id, at, rest
                if not inside:
                    return
                file_id, at, rest, skip = f, start, b"", start > 0
            if not inside and skip:
                return  # all of it lies within one line
            *whole, rest = (rest + data).split(b"\n")
            for x in whole:
                if not skip:
                    yield file_id, at, x
                skip, at = False, at + len(x) + 1
                if not inside:
                    return
        if not inside and len(p.after) == AHEAD:
            raise ParinflateError(f"a line is longer than {AHEAD} row groups of the index")
        if file_id is not None and rest and not skip:
            yield file_id, at, rest

    def read(self, partition: Groups | Whole) -> Iterator[pa.RecordBatch]:
        if self.format == "bytes":
            for f, no, at, data, _ in self._pieces(partition):
                yield pa.RecordBatch.from_arrays([pa.array([f]), pa.array([no]), pa.array([at]), pa.array([data], pa.binary())], ["file_id", "point_no", "out_start", "bytes"])
            return
        rows: list[tuple[int, int, bytes]] = []
        for x in self._lines(partition):
            rows.append(x)
            if len(rows) >= BATCH:
                yield self._batch(rows)
                rows = []
        if rows:
            yield self._batch(rows)

    def _batch(self, rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
        texts = [x.decode("utf-8", "replace") for _, _, x in rows]
        if self.format == "lines":
            return pa.RecordBatch.from_arrays([pa.array([f for f, _, _ in rows], pa.int64()), pa.array([a for _, a, _ in rows], pa.int64()), pa.array(texts)], ["file_id", "out_pos", "line"])
        kind = to_arrow_schema(self.schema)
        if self.format == "json":
            found = [json.loads(t) if t.strip() else {} for t in texts]
            columns = [[r.get(n) for r in found] for n in kind.names]
        else:
            found = list(csv.reader(io_.StringIO("\n".join(texts))))
            columns = [[r[k] if k < len(r) and r[k] != "" else None for r in found] for k in range(len(kind.names))]
            columns = [pa.array(c, pa.string()).cast(t) for c, t in zip(columns, kind.types, strict=True)]
        return pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, t) for c, t in zip(columns, kind.types, strict=True)], schema=kind)


class _Pruned(_Plain):
    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            op = _COMPARE.get(type(f))
            if op and len(f.attribute) == 1 and f.attribute[0] in ("file_id", "point_no", "out_start"):
                self.limits.append((f.attribute[0], op, f.value))
            yield f  # points are pruned; Spark still tests the rows


def _place(path: str):
    if (p := local(path)) is not None:
        from pyarrow.fs import LocalFileSystem

        return p, LocalFileSystem()
    from pyarrow.fs import FileSystem

    fs, p = FileSystem.from_uri(path)
    return p, fs


def _files(path: str) -> list[str]:
    """Files of a folder, or the file."""
    from pyarrow.fs import FileSelector, FileType

    p, fs = _place(path)
    if fs.get_file_info(p).type != FileType.Directory:
        return [path]
    lead = "" if local(path) is not None else path[: path.index("://") + 3]
    return sorted(lead + f.path for f in fs.get_file_info(FileSelector(p, recursive=True)) if f.type == FileType.File and not f.base_name.startswith(("_", ".")))


def members(path: str, start: int = 0, stop: int | None = None, step: int = 1 << 20, most: int = 8 << 20) -> Iterator[bytes]:
    """The plain way: from front to back, all members of bytes [start, stop), in pieces of bounded size."""
    with Ranged(path) as read:
        d, at = zlib.decompressobj(31), start
        while (stop is None or at < stop) and (part := read(at, step if stop is None else min(step, stop - at))):
            at += len(part)
            while part:
                if d.eof:
                    if not part.strip(b"\0"):
                        break
                    d = zlib.decompressobj(31)
                if out := d.decompress(part, most):
                    yield out
                part = d.unused_data if d.eof else d.unconsumed_tail
        if not d.eof and at > start:
            raise ParinflateError(f"{path} is truncated")


def serial(path: str) -> Iterator[bytes]:
    """One task, from front to back, all members."""
    return members(path)


class _Writer(DataSourceArrowWriter):
    """One file per task, made whole only when the task ends."""

    def __init__(self, options, overwrite: bool):
        self.path, self.layout, self.level, self.overwrite = options["path"], options.get("layout", "single"), int(options.get("level", 6)), overwrite
        self.job = uuid.uuid4().hex[:8]

    def write(self, iterator: Iterator[pa.RecordBatch]) -> WriterCommitMessage:
        from pyspark import TaskContext

        from parinflate.sources.writers import CUT, _File, bgzf, gzip_member

        t = TaskContext.get()
        out = _File(f"{self.path.rstrip('/')}/part-{t.partitionId():05}-{self.job}-{t.taskAttemptId()}.gz", self.layout, self.level)
        rows = 0
        for batch in iterator:
            lines = [x.encode() if isinstance(x, str) else x or b"" for x in batch.column(0).to_pylist()]
            rows += len(lines)
            data = b"".join(x + b"\n" for x in lines)
            if data:
                out.add((bgzf(data, self.level) if self.layout == "bgzf" else gzip_member(data, self.level)) if self.layout in CUT else data, len(data), zlib.crc32(data))
        out.close()
        return Written(out.path, rows)

    def commit(self, messages: list[WriterCommitMessage | None]) -> None:
        if self.overwrite:
            kept = {os.path.basename(m.file) for m in messages if m}
            p, fs = _place(self.path)
            for f in _files(self.path):
                if os.path.basename(f) not in kept:
                    fs.delete_file(_place(f)[0])

    def abort(self, messages: list[WriterCommitMessage | None]) -> None:
        for m in messages:
            if m:
                p, fs = _place(m.file)
                fs.delete_file(p)


@dataclass
class Written(WriterCommitMessage):
    file: str
    rows: int


class ParinflateSource(DataSource):
    """Registered as ``parinflate``."""

    @classmethod
    def name(cls) -> str:
        return "parinflate"

    def schema(self) -> str:
        kind = self.options.get("format", "bytes")
        if kind in ("csv", "json"):
            raise ValueError(f"format {kind} needs a schema")
        return schemas.STREAM if kind == "bytes" else LINES

    def reader(self, schema) -> DataSourceReader:
        return (_Pruned if self.options.get("pushdown", "false") == "true" else _Plain)(self.options, schema)

    def writer(self, schema, overwrite: bool) -> DataSourceArrowWriter:
        if len(schema.fields) != 1:
            raise ValueError("one column of lines is written")
        if self.options.get("layout", "single") not in ("single", "bgzf", "multi_member"):
            raise ValueError("layout must be single, bgzf or multi_member")
        return _Writer(self.options, overwrite)
