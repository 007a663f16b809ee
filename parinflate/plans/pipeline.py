"""The whole way: files to bytes, lines or records, with the options of every stage; and recovery of damaged files."""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parinflate import schemas
from parinflate.functions import probe
from parinflate.functions.gzipfmt import CorruptBlock, NonTextByte, ParinflateError, parse_header
from parinflate.operators import finder, index, records, spans, windows
from parinflate.runtime import materialize, spread
from parinflate.sources.io import Ranged, archives


def _archive(spark: SparkSession, source: str | DataFrame) -> DataFrame:
    return archives(spark, source) if isinstance(source, str) else source


def decompress(spark: SparkSession, source: str | DataFrame, *, slot_bytes: int = spans.SLOT_BYTES, variant: str = "packed", mode: str = "scan", group: int = windows.GROUP, materialize_as: str = "redecode", ordered: bool = True, fallback: bool = True, on_error: str = "fail", max_out_bytes: int = 64 << 20, max_rounds: int = 32, verify_crc: bool = True, upto_byte: int | None = None) -> DataFrame:
    """(file_id, point_no, out_start, bytes) of the decompressed files.

    ``materialize_as`` redecode: windows are found first and every span is inflated again with its window; symbols: stage 1 keeps its symbols,
    two bytes for one, and windows replace their markers. ``variant`` text_only is the predecessor: content must be bytes 9 to 126.

    ``on_error`` fail: a damaged file is an error. skip: what links up to the first damage of each file, with a column ``status``,
    complete, cut or bad_checksum. recover: (file_id, start_bit, status, bytes) of :func:`recover`. Checksums of whole files are verified.
    """
    archive = _archive(spark, source)
    if on_error == "recover":
        return recover(spark, archive, slot_bytes)
    idx, counters = index.build(archive, slot_bytes, variant, mode, group, upto=upto_byte, max_rounds=max_rounds, on_error=on_error, fallback=fallback)
    if verify_crc and upto_byte is None and on_error == "fail":
        index.verify(idx, strict=True)
    if upto_byte is not None:
        idx = index.points_upto(idx, upto_byte)
    out = kept_symbols(idx) if materialize_as == "symbols" else index.read(idx, max_out_bytes)
    if variant == "text_only":
        out = out.mapInArrow(_text_only, schemas.STREAM)
    if on_error == "skip":
        cut = counters["broken"].select(F.col("file_id").alias("cut_id"), F.lit("cut").alias("said"))
        wrong = index.verify(idx).where(~F.col("ok")).select(F.col("file_id").alias("cut_id"), F.lit("bad_checksum").alias("said")).distinct()
        said = materialize(cut.union(wrong).groupBy("cut_id").agg(F.max("said").alias("said")), "said")  # cut goes before bad_checksum
        out = out.join(said, F.col("file_id") == F.col("cut_id"), "left").withColumn("status", F.coalesce("said", F.lit("complete"))).drop("cut_id", "said")
    return out.repartitionByRange("file_id", "out_start").sortWithinPartitions("file_id", "out_start") if ordered else out


def _text_only(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    lo, hi = finder.TEXT
    for batch in batches:
        for x in batch.column("bytes"):
            a = np.frombuffer(x.as_py(), np.uint8)
            if ((a < lo) | (a > hi)).any():
                raise NonTextByte(f"a byte outside {lo} to {hi}")
        yield batch


def kept_symbols(idx: DataFrame) -> DataFrame:
    """Stage 2 from stage 1's symbols, which are written and meet the windows of their spans by a join."""
    kept = materialize(spans.symbols(idx.drop("window")), "symbols")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                r = batch.slice(k, 1).to_pylist()[0]
                yield pa.RecordBatch.from_arrays([pa.array([r["file_id"]]), pa.array([r["point_no"]]), pa.array([r["out_start"]]), pa.array([probe.replaced(r["symbols"], r["window"])], pa.binary())], ["file_id", "point_no", "out_start", "bytes"])

    where = idx.select("file_id", "start_bit", "point_no", F.col("out_start").alias("base"), "window")
    return kept.join(where, ["file_id", "start_bit"]).select("file_id", "point_no", (F.col("base") + F.col("off")).alias("out_start"), "symbols", "window").mapInArrow(run, schemas.STREAM)


def resolve(idx: DataFrame, serial: bool = False) -> DataFrame:
    """Stage 2 by whole-chunk marker replacement: the symbols of a span meet its window in the task that decodes it. ``serial`` is the ablation in which one task per file does all of it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                r = batch.slice(k, 1).to_pylist()[0]
                at = r["out_start"]
                with Ranged(r["path"]) as read:
                    s = spans.stream(r, None, read)
                    for p in s:
                        if p.data:
                            yield pa.RecordBatch.from_arrays([pa.array([r["file_id"]]), pa.array([r["point_no"]]), pa.array([at]), pa.array([probe.apply(p, r["window"])], pa.binary())], ["file_id", "point_no", "out_start", "bytes"])
                        at += len(p.data)
                if not s.ok:
                    raise CorruptBlock(f"{r['path']} from bit {r['start_bit']}: {s.reason}")

    rows = idx.repartition("file_id").sortWithinPartitions("file_id", "out_start") if serial else index.spread_points(idx)
    return rows.mapInArrow(run, schemas.STREAM)


def lines(spark: SparkSession, source: str | DataFrame, numbered: bool = False, **how) -> DataFrame:
    idx, _ = index.build(_archive(spark, source), **how)
    return records.lines(idx, numbered)


def table(spark: SparkSession, source: str | DataFrame, schema: str, format: str = "json", **how) -> DataFrame:
    idx, _ = index.build(_archive(spark, source), **how)
    return records.json_table(idx, schema) if format == "json" else records.csv_table(idx, schema)


def recover(spark: SparkSession, source: str | DataFrame, slot_bytes: int = spans.SLOT_BYTES, unknown: bytes = b"?") -> DataFrame:
    """(file_id, start_bit, off, status, bytes): what decodes of damaged files, in cells from byte ``off`` of a span. Spans before the damage are sound;
    after it, decoding goes on at the next block from which it reaches the span's end, and bytes that came from lost history are ``unknown``.
    What a broken span gives before the break is damaged."""
    archive = _archive(spark, source)
    slots = materialize(spans.plan(archive, slot_bytes), "slots")
    todo = materialize(spans.hints(slots, materialize(spans.find(slots), "candidates")), "todo")
    stage1 = materialize(spans.decode(todo), "spans").drop("tail_map", "pieces")
    names = ["file_id", "start_bit", "off", "status", "bytes"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                def cells(status: str, at: int, pieces: Iterator[bytes]) -> Iterator[pa.RecordBatch]:
                    off = 0
                    for data in pieces:
                        yield pa.RecordBatch.from_arrays([pa.array([r["file_id"]]), pa.array([at]), pa.array([off]), pa.array([status]), pa.array([data], pa.binary())], names)  # noqa: B023
                        off += len(data)

                def whole(of: dict) -> Iterator[bytes]:
                    return (probe.apply(p, unknown * probe.WINDOW) for p in spans.stream(of, None, read) if p.data)  # noqa: B023

                with Ranged(r["path"]) as read:
                    if r["ok"]:
                        yield from cells("partial" if r["n_markers"] else "sound", r["start_bit"], whole(r))
                        continue
                    yield from cells("damaged", r["start_bit"], prefix(read, r["start_bit"], r["end_bit"] or 8 * r["size"], r["kind"]))
                    if found := _next_sound(read, r):
                        of, n_markers = found
                        yield from cells("partial" if n_markers else "sound", of["start_bit"], whole(of))

    return spread(stage1, stage1.count(), 0).mapInArrow(run, "file_id long, start_bit long, off long, status string, bytes binary")


def _next_sound(read: Ranged, r: dict) -> tuple[dict, int] | None:
    """The first block or member inside a broken span from which its end is reached, and how many of its bytes hang on lost history."""
    lo, stop = r["start_bit"] // 8, r["end_bit"] or 8 * r["size"]
    buf = read(lo, min(r["size"], stop // 8 + 64) - lo)
    for _, bit, kind in finder.candidates(buf, r["start_bit"] - 8 * lo + 1, stop - 8 * lo, final=lo + len(buf) >= r["size"]):
        of = r | {"start_bit": bit + 8 * lo, "kind": kind}
        d = probe.Summary(spans.stream(of, None, read))
        if d.ok:
            return of, d.n_markers
    return None


def prefix(read: Callable[[int, int], bytes], start_bit: int, end_bit: int, kind: str, step: int = 1024) -> Iterator[bytes]:
    """Bytes up to the first error, ``step`` by ``step`` bytes of input; lost history reads as question marks."""
    at, stop = start_bit >> 3, min((end_bit >> 3) + 64, end_bit + 7 >> 3)
    d = zlib.decompressobj(-15) if kind == "member" else zlib.decompressobj(-15, zdict=b"?" * probe.WINDOW)
    if kind == "member":
        try:
            at += parse_header(read(at, 1 << 16), 0).end
        except ParinflateError:
            return
    first = kind != "member"
    while at < stop and not d.eof:
        part = read(at, min(step, stop - at))
        if not part:
            return
        at += len(part)
        try:
            out = d.decompress(probe.primed(part, start_bit & 7, len(part)) if first else part)
        except zlib.error:
            return
        first = False
        if out:
            yield out
