"""From files to linked spans: plan slots, find a block in each, decode from block to block, accept what links, repair what does not."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from parinflate import schemas
from parinflate.functions import probe
from parinflate.functions.gzipfmt import CorruptBlock
from parinflate.operators import finder
from parinflate.runtime import materialize, ship, spread
from parinflate.sources.io import LOOKAHEAD, Ranged, read_range

SLOT_BYTES = 4 << 20


def plan(archive: DataFrame, slot_bytes: int = SLOT_BYTES) -> DataFrame:
    """Equal slots of each file; at least one."""
    n = F.greatest(F.lit(1), F.ceil(F.col("size") / slot_bytes)).cast("long")
    slots = archive.withColumn("slot_no", F.explode(F.sequence(F.lit(0).cast("long"), n - 1)))
    return slots.select("file_id", "path", "size", "slot_no", (F.col("slot_no") * slot_bytes * 8).alias("guess_bit"), F.least((F.col("slot_no") + 1) * slot_bytes, F.col("size")).alias("limit")).withColumn("limit_bit", F.col("limit") * 8).drop("limit")


def find(slots: DataFrame, confirm: int = 1024, variant: str = "packed", container: str = "gzip", work: tuple[int, int] | None = None) -> DataFrame:
    """At most one candidate per slot: the first confirmed one. A file's first slot starts at its header. ``work``: how many slots and bytes, where that is known."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                if r["slot_no"] == 0:
                    rows.append((r["file_id"], 0, 0, 0, "member" if container == "gzip" else "block"))
                    continue
                lo, hi = max(0, r["guess_bit"] // 8 - 8), r["limit_bit"] // 8
                buf = read_range(r["path"], lo, hi - lo + LOOKAHEAD)
                for a, b, kind in finder.candidates(buf, r["guess_bit"] - 8 * lo, r["limit_bit"] - 8 * lo, confirm, variant, final=lo + len(buf) >= r["size"]):
                    rows.append((r["file_id"], r["slot_no"], a + 8 * lo, b + 8 * lo, kind))
                    break
            yield pa.RecordBatch.from_pylist([dict(zip(("file_id", "slot_no", "start_bit", "last_bit", "kind"), x, strict=True)) for x in rows], schema=pa.schema([("file_id", pa.int64()), ("slot_no", pa.int64()), ("start_bit", pa.int64()), ("last_bit", pa.int64()), ("kind", pa.string())]))

    ship(slots.sparkSession)
    return _spread(slots, work).mapInArrow(run, schemas.CANDIDATE)


def _spread(rows: DataFrame, work: tuple[int, int] | None = None) -> DataFrame:
    """Slots or spans, a thin table, dealt to tasks by their number and the bytes of their files."""
    if work is not None:
        return spread(rows, *work)
    n, files = rows.count(), rows.groupBy("file_id").agg(F.max("size").alias("size"))
    return spread(rows, n, files.agg(F.sum("size")).first()[0] or 0)


def hints(slots: DataFrame, found: DataFrame) -> DataFrame:
    """Spans to decode: from each candidate to the next one of its file, or to the end. A stored candidate means any bit of its range; the last is its name, and all but it decode alike."""
    w = Window.partitionBy("file_id").orderBy("start_bit")
    files = slots.select("file_id", "path", "size").distinct()
    spans = found.select("file_id", F.col("last_bit").alias("start_bit"), "kind").withColumns({"end_bit": F.lead("start_bit").over(w), "end_kind": F.lead("kind").over(w)})
    return spans.join(files, "file_id").select("file_id", "path", "size", "start_bit", "end_bit", "kind", "end_kind")


def stream(r: dict, window: bytes | None, read: Ranged, container: str = "gzip", fallback: bool = True) -> probe.SpanStream:
    """The decoder of a span or index point."""
    start, kind = r["start_bit"], "member" if r["kind"] == "member" else "block"
    if container != "gzip" and start == 0:  # the stream begins after the container's own header
        start, window = (16 if container == "zlib" else 0), b""
    end_kind = r["end_kind"] if r["end_kind"] in ("member", "stored") else "block"
    return probe.SpanStream(read, r["size"], start, r["end_bit"], kind, end_kind, window, container, fallback)


_PIECES = pa.list_(pa.struct([("n", pa.int64()), ("crc", pa.int64()), ("ends", pa.bool_()), ("footer_crc", pa.int64()), ("isize", pa.int64())]))
_FOUND = [("ok", pa.bool_()), ("reason", pa.string()), ("out_len", pa.int64()), ("n_markers", pa.int64()), ("last_marker", pa.int64()), ("fallback_pos", pa.int64()), ("tail_map", pa.binary()), ("pieces", _PIECES)]


def decode(spans: DataFrame, fallback: bool = True, container: str = "gzip", work: tuple[int, int] | None = None) -> DataFrame:
    """Stage 1 of every span without its history: sizes, markers, the tail as a function of the window, checksums of pieces; no payload. A task holds a few MB of a span at a time, however long or dense it is."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            schema = pa.schema([*batch.schema, *_FOUND])
            for r in batch.to_pylist():
                with Ranged(r["path"]) as read:
                    d = probe.Summary(stream(r, None, read, container, fallback))
                found = {"ok": d.ok, "reason": d.reason, "out_len": d.out_len, "n_markers": d.n_markers, "last_marker": d.last_marker, "fallback_pos": d.fallback_at, "tail_map": d.tail_map().tobytes() if d.ok else None, "pieces": d.pieces}
                yield pa.RecordBatch.from_pylist([r | found], schema=schema)

    ship(spans.sparkSession)
    return _spread(spans, work).mapInArrow(run, schemas.SPAN)


def symbols(spans: DataFrame, container: str = "gzip") -> DataFrame:
    """(file_id, start_bit, off, symbols): stage 1 of spans, kept: 16 bits for each byte, in cells of bounded size from byte ``off`` of the span."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                off = 0
                with Ranged(r["path"]) as read:
                    s = stream(r, None, read, container)
                    for p in s:
                        if p.data:
                            yield pa.RecordBatch.from_arrays([pa.array([r["file_id"]]), pa.array([r["start_bit"]]), pa.array([off]), pa.array([probe.symbols(p).tobytes()], pa.binary())], ["file_id", "start_bit", "off", "symbols"])
                        off += len(p.data)
                if not s.ok:
                    raise CorruptBlock(f"{r['path']} from bit {r['start_bit']}: {s.reason}")

    ship(spans.sparkSession)
    return _spread(spans).mapInArrow(run, "file_id long, start_bit long, off long, symbols binary")


def broken(spans: DataFrame) -> DataFrame:
    """(file_id, bad_bit): where each broken file's chain ends. Ends are the starts of the next candidates, so a chain breaks exactly where a span is not ok; what follows is unproved, as its start may be a false candidate."""
    return spans.where(~F.col("ok")).groupBy("file_id").agg(F.min("start_bit").alias("bad_bit"))


_STATE = ("file_id", "path", "size", "start_bit", "end_bit", "kind", "end_kind", "ok")


def repair(todo: DataFrame, max_rounds: int = 32, fallback: bool = True, container: str = "gzip", work: tuple[int, int] | None = None) -> tuple[DataFrame, int, bool]:
    """(linked spans, rounds, whether all link): decode ``todo`` and mend what does not link.

    A span that does not end at the next candidate is decoded again to a later one, and what it covers falls out. The first
    rounds extend the first span of every run of bad ones by one candidate. Later rounds extend the first of each file by twice
    as many as before: a boundary skipped costs parallelism, never a wrong result. Each round writes what it decodes and
    a thin table of who is in the chain; tail maps are not written again.
    """
    parts = [materialize(decode(todo, fallback, container, work), "spans")]
    state = parts[0].select(*_STATE, F.lit(0).alias("part"))
    reach = rounds = 0
    clean = False
    for rounds in range(max_rounds + 1):
        clean = not state.where(~F.col("ok")).take(1)
        if rounds == max_rounds or clean:
            break
        reach = 1 if rounds < 4 else 2 * reach
        w = Window.partitionBy("file_id").orderBy("start_bit")
        rows = state.withColumns({"rn": F.row_number().over(w), "before": F.lag("ok").over(w), "n": F.count(F.lit(1)).over(Window.partitionBy("file_id"))})
        bad = rows.where(~F.col("ok") & F.coalesce("before", F.lit(True)) & (F.col("rn") < F.col("n")))
        if reach > 1:
            bad = bad.join(broken(state).withColumnRenamed("bad_bit", "start_bit"), ["file_id", "start_bit"], "left_semi")
        bad = materialize(bad.select("file_id", F.col("start_bit").alias("from_bit"), F.col("rn").alias("from_rn"), F.least(F.col("rn") + reach, F.col("n")).alias("to_rn")), "bad")
        if not bad.take(1):
            break
        ends = rows.join(bad, "file_id").where("rn = to_rn").select("file_id", F.col("from_bit").alias("start_bit"), F.col("end_bit").alias("new_end"), F.col("end_kind").alias("new_kind"))
        again = state.select("file_id", "path", "size", "start_bit", "kind").join(ends, ["file_id", "start_bit"]).select("file_id", "path", "size", "start_bit", F.col("new_end").alias("end_bit"), "kind", F.col("new_kind").alias("end_kind"))
        gone = rows.join(bad, "file_id").where("rn >= from_rn AND rn <= to_rn").select("file_id", "start_bit").distinct()
        parts.append(materialize(decode(materialize(again, "again"), fallback, container), "spans"))
        fresh = parts[-1].select(*_STATE, F.lit(len(parts) - 1).alias("part"))
        state = materialize(state.join(gone, ["file_id", "start_bit"], "left_anti").unionByName(fresh), "state")
    if len(parts) == 1:
        return parts[0], rounds, clean
    # Rows of a part that later parts replaced are few; what is left of each part stays where it is.
    out = None
    for k, part in enumerate(parts):
        left = state.where(F.col("part") == k).select("file_id", "start_bit")
        stale = materialize(part.select("file_id", "start_bit").join(left, ["file_id", "start_bit"], "left_anti"), "stale")
        kept = part.join(stale, ["file_id", "start_bit"], "left_anti")
        out = kept if out is None else out.unionByName(kept)
    return out, rounds, clean
