"""The seek index: points of (compressed bit, decompressed byte, window), kept as a table; reading by it needs one stock inflate."""

from __future__ import annotations

import json
import struct
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from parinflate import schemas
from parinflate.functions import crc as crc_
from parinflate.functions import probe
from parinflate.functions.gzipfmt import ChecksumMismatch, CorruptBlock
from parinflate.operators import finder
from parinflate.operators import spans as spans_
from parinflate.operators import windows as windows_
from parinflate.runtime import materialize, ship, spread
from parinflate.sources.io import LOOKAHEAD, Ranged


def from_spans(spans: DataFrame, mode: str = "scan", group: int = windows_.GROUP) -> DataFrame:
    """Points of linked spans: output offsets by a running sum, windows by propagation."""
    w = Window.partitionBy("file_id").orderBy("start_bit")
    before = w.rowsBetween(Window.unboundedPreceding, -1)
    placed = spans.select("file_id", "path", "size", "start_bit", "end_bit", "kind", "end_kind", "out_len").withColumns({"point_no": (F.row_number().over(w) - 1).cast("long"), "out_start": F.coalesce(F.sum("out_len").over(before), F.lit(0)).cast("long")})
    found = windows_.propagate(spans, mode, group)
    return placed.join(found, ["file_id", "start_bit"]).select([c.split()[0] for c in schemas.INDEX.split(", ")])


def build(archive: DataFrame, slot_bytes: int = spans_.SLOT_BYTES, variant: str = "packed", mode: str = "scan", group: int = windows_.GROUP, confirm: int = 1024, upto: int | None = None, max_rounds: int = 32, on_error: str = "fail", container: str = "gzip", fallback: bool = True) -> tuple[DataFrame, dict]:
    """(index, counters). With ``upto`` only as many slots are read as hold that decompressed byte, by doubling.

    Where ``on_error`` is not fail, the index ends at the first damage of each file, and the counter ``broken`` is the table (file_id, bad_bit) of
    the files whose index is not whole.
    """
    ship(archive.sparkSession)
    slots = spans_.plan(archive, slot_bytes)
    # One row: files, bytes and slots, by which all work is dealt.
    known = archive.agg(F.count(F.lit(1)).alias("files"), F.sum("size").alias("bytes"), F.sum(F.greatest(F.lit(1), F.ceil(F.col("size") / slot_bytes))).cast("long").alias("slots")).first()
    work, limit = (known.slots or 0, known.bytes or 0), None
    if upto is not None:
        limit = 1 + max(1, -(-upto // (4 * slot_bytes)))
    while True:
        part = slots if limit is None else slots.where(F.col("slot_no") < limit)
        found = materialize(spans_.find(part, confirm, variant, container, work), "candidates")
        todo = spans_.hints(part, found)
        if limit is not None:  # the last span has no end yet unless the file ends there
            todo = todo.where(F.col("end_bit").isNotNull() | (F.col("size") <= limit * slot_bytes))
        spans, rounds, clean = spans_.repair(todo, max_rounds, fallback, container, work)
        if limit is None or spans.groupBy("file_id").agg(F.sum("out_len").alias("n"), F.max("size").alias("size")).where((F.col("n") >= upto) | (F.col("size") <= limit * slot_bytes)).count() == known.files:
            break
        limit *= 2
    sound, broken, damaged = spans, None, 0
    if not clean:
        broken = materialize(spans_.broken(spans), "broken")
        damaged = broken.count()
        if on_error == "fail":
            r = spans.where(~F.col("ok")).select("path", "start_bit", "reason").first()
            raise CorruptBlock(f"{r.path} from bit {r.start_bit}: {r.reason}")
        # What links, up to the first break of each file; the rest is for recovery.
        sound = materialize(spans.join(broken, "file_id", "left").where(F.col("bad_bit").isNull() | (F.col("start_bit") < F.col("bad_bit"))).drop("bad_bit"), "sound")
    index = materialize(from_spans(sound, mode, group), "index")
    broken = broken if broken is not None else sound.sparkSession.createDataFrame([], "file_id long, bad_bit long")
    counters = {"slots": work[0], "candidates": found.count(), "spans": index.count(), "rounds": rounds, "damaged": damaged}
    return index, counters | {"linked": sound, "broken": broken}


#: Points of a row group of a saved index.
GROUP_POINTS = 256


def save(index: DataFrame, path: str) -> None:
    """One sorted Parquet table; windows compress with zstd. Row groups are small, so that their statistics find a position."""
    ranged = index.repartitionByRange("file_id", "out_start").sortWithinPartitions("file_id", "out_start")
    ranged.write.mode("overwrite").option("compression", "zstd").option("parquet.block.row.count.limit", GROUP_POINTS).parquet(path)


def load(spark, path: str) -> DataFrame:
    return spark.read.schema(schemas.INDEX).parquet(path)


def respace(index: DataFrame, spacing: int) -> DataFrame:
    """Merge points so that each holds about ``spacing`` decompressed bytes; the first point of a group stays and takes the group's length and end."""
    g = F.floor(F.col("out_start") / spacing).alias("g")
    first = F.min_by(F.struct("start_bit", "kind", "window"), "point_no").alias("a")
    last = F.max_by(F.struct("end_bit", "end_kind"), "point_no").alias("z")
    merged = index.groupBy("file_id", "path", "size", g).agg(first, last, F.min("out_start").alias("out_start"), F.sum("out_len").alias("out_len"))
    no = (F.row_number().over(Window.partitionBy("file_id").orderBy("out_start")) - 1).cast("long").alias("point_no")
    return merged.select("file_id", "path", "size", no, "a.start_bit", "z.end_bit", "a.kind", "z.end_kind", "out_start", "out_len", "a.window")


def ahead(read: Ranged, size: int, bit: int, stop: int, look: int = 1 << 20) -> Iterator[tuple[int, int, str]]:
    """Candidates in [bit, stop), ``look`` bytes at a time."""
    while bit < stop:
        lo = max(0, bit // 8 - 8)
        buf = read(lo, look + LOOKAHEAD)
        to = min(8 * len(buf), 8 * look, stop - 8 * lo)
        for a, b, kind in finder.candidates(buf, bit - 8 * lo, to, final=lo + len(buf) >= size):
            yield a + 8 * lo, b + 8 * lo, kind
        bit = 8 * lo + to


def walk(r: dict, spacing_bits: int) -> Iterator[dict]:
    """Points from the one in ``r`` on up to its end, each at the next block that is found after ``spacing_bits`` of input."""
    at, kind, window, out = r["start_bit"], r["kind"], r["window"], r["out_start"]
    end = r["end_bit"] if r["end_bit"] is not None else 8 * r["size"]
    with Ranged(r["path"]) as read, Ranged(r["path"]) as again:
        while at is not None and at < end or at == r["start_bit"]:
            found = None
            for _, b, k in ahead(read, r["size"], at + spacing_bits, end):
                d = probe.Summary(spans_.stream({"size": r["size"], "start_bit": at, "end_bit": b, "kind": kind, "end_kind": k}, window, again))
                if d.ok:
                    found = b, k
                    break
            else:
                d = probe.Summary(spans_.stream({"size": r["size"], "start_bit": at, "end_bit": r["end_bit"], "kind": kind, "end_kind": r["end_kind"]}, window, again))
                if not d.ok:
                    raise CorruptBlock(f"{r['path']} from bit {at}: {d.reason}")
            stop, stop_kind = found or (r["end_bit"], r["end_kind"])
            yield r | {"start_bit": at, "end_bit": stop, "kind": kind, "end_kind": stop_kind, "out_start": out, "out_len": d.out_len, "window": window}
            if not found:
                return
            window = probe.step(d.tail_map(), window)
            out, at, kind = out + d.out_len, stop, stop_kind


_INDEX = pa.schema([(c.split()[0], {"long": pa.int64(), "string": pa.string(), "binary": pa.binary()}[c.split()[1]]) for c in schemas.INDEX.split(", ")])


def split(index: DataFrame, spacing: int) -> DataFrame:
    """Points at most about ``spacing`` decompressed bytes apart, where blocks allow it: dense points are walked through again in the task that has their window."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for r in _rows(batches):
            end = r["end_bit"] if r["end_bit"] is not None else 8 * r["size"]
            for x in walk(r, max(64, (end - r["start_bit"]) * spacing // max(1, r["out_len"]))):
                yield pa.RecordBatch.from_pylist([x], schema=_INDEX)

    ship(index.sparkSession)
    dense = materialize(index.where(F.col("out_len") > spacing), "dense")
    parts = index.where(F.col("out_len") <= spacing).unionByName(spread_points(dense).mapInArrow(run, schemas.INDEX))
    no = (F.row_number().over(Window.partitionBy("file_id").orderBy("out_start", "start_bit")) - 1).cast("long")
    return parts.withColumn("point_no", no)


def export(index: DataFrame, folder: str) -> list[str]:
    """One compact file per archive, for exchange: a line of JSON with the path and size, then for each point its numbers and its compressed window."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from parinflate.sources.writers import open_out

        now, out = None, None
        for r in _rows(batches):
            if r["file_id"] != now:
                if out is not None:
                    out.close()
                now, name = r["file_id"], f"{folder.rstrip('/')}/{r['file_id']}.points"
                out = open_out(name)
                out.write(json.dumps({"file_id": r["file_id"], "path": r["path"], "size": r["size"]}).encode() + b"\n")
                yield pa.RecordBatch.from_arrays([pa.array([name])], ["name"])
            w = zlib.compress(r["window"], 6)
            out.write(struct.pack(_POINT, r["point_no"], r["start_bit"], -1 if r["end_bit"] is None else r["end_bit"], _KINDS.index(r["kind"]), _KINDS.index(r["end_kind"]), r["out_start"], r["out_len"], len(w)) + w)
        if out is not None:
            out.close()

    ship(index.sparkSession)
    files = index.select("file_id").distinct().count()
    ranged = index.repartition(max(1, min(files, 4 * index.sparkSession.sparkContext.defaultParallelism)), "file_id").sortWithinPartitions("file_id", "point_no")
    return sorted(r.name for r in ranged.mapInArrow(run, "name string").collect())


_POINT, _KINDS = "<qqqbbqqi", (None, "member", "dynamic", "stored", "block")


def imported(spark, names: list[str]) -> DataFrame:
    """An index from files that :func:`export` wrote."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name in batch.column(0).to_pylist():
                with Ranged(name) as read:
                    line = read(0, 1 << 16).split(b"\n")[0]
                    head, at = json.loads(line), len(line) + 1
                    while raw := read(at, struct.calcsize(_POINT)):
                        no, a, b, k, z, start, n, w = struct.unpack(_POINT, raw)
                        at += len(raw) + w
                        row = head | {"point_no": no, "start_bit": a, "end_bit": None if b < 0 else b, "kind": _KINDS[k], "end_kind": _KINDS[z], "out_start": start, "out_len": n, "window": zlib.decompress(read(at - w, w))}
                        yield pa.RecordBatch.from_pylist([row], schema=_INDEX)

    ship(spark)
    return spread(spark.createDataFrame([(n,) for n in names], "name string"), len(names), 0).mapInArrow(run, schemas.INDEX)


def point_parts(r: dict, container: str = "gzip") -> Iterator[probe.Part]:
    """Parts of one point, each of bounded size; an error ends the iteration."""
    n = ((8 * r["size"] if r["end_bit"] is None else r["end_bit"]) - r["start_bit"]) // 8
    with Ranged(r["path"], min(4 << 20, n + (1 << 10))) as read:  # no more than the point has is read for it
        s = spans_.stream(r, r["window"], read, container)
        yield from s
    if not s.ok:
        raise CorruptBlock(f"{r['path']} from bit {r['start_bit']}: {s.reason}")


def point_bytes(r: dict, container: str = "gzip") -> Iterator[bytes]:
    return (p.data for p in point_parts(r, container) if p.data)


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    """Points one by one, as each holds a window."""
    for batch in batches:
        for k in range(batch.num_rows):
            yield batch.slice(k, 1).to_pylist()[0]


def spread_points(index: DataFrame) -> DataFrame:
    """Points dealt to tasks by their number and by what is to be read: their files' bytes and, where it is more, an eighth of what they decompress to."""
    n = index.agg(F.count(F.lit(1)).alias("n"), F.sum("out_len").alias("out")).first()
    files = index.groupBy("file_id").agg(F.max("size").alias("size")).agg(F.sum("size")).first()[0] or 0
    return spread(index, n.n, max(files, (n.out or 0) // 8))


def read(index: DataFrame, most: int = 64 << 20, container: str = "gzip") -> DataFrame:
    """(file_id, point_no, out_start, bytes): every point inflated where it is read; cells have at most ``most`` bytes, and no more than two are held."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for r in _rows(batches):
            at, held, size = r["out_start"], [], 0

            def cell() -> pa.RecordBatch:
                return pa.RecordBatch.from_arrays([pa.array([r["file_id"]]), pa.array([r["point_no"]]), pa.array([at]), pa.array([b"".join(held)], pa.binary())], ["file_id", "point_no", "out_start", "bytes"])  # noqa: B023

            for data in point_bytes(r, container):
                for lo in range(0, len(data), most):
                    part = data[lo : lo + most]
                    if size and size + len(part) > most:
                        yield cell()
                        at, held, size = at + size, [], 0
                    held.append(part)
                    size += len(part)
            if size or not r["out_len"]:
                yield cell()

    ship(index.sparkSession)
    return spread_points(index).mapInArrow(run, schemas.STREAM)


def checksums(index: DataFrame, container: str = "gzip") -> DataFrame:
    """(file_id, point_no, seq, n, crc, ends, footer_crc, isize) of every piece of a member in a point, from bytes that are dropped at once."""
    kind = pa.schema([(c, pa.bool_() if c == "ends" else pa.int64()) for c in ("file_id", "point_no", "seq", "n", "crc", "ends", "footer_crc", "isize")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for r in _rows(batches):
            rows, n, c = [], 0, 0

            def piece(p: probe.Part) -> dict:
                return {"file_id": r["file_id"], "point_no": r["point_no"], "seq": len(rows), "n": n, "crc": c, "ends": p.ends, "footer_crc": p.crc, "isize": p.isize}  # noqa: B023

            for p in point_parts(r, container):
                n, c = n + len(p.data), zlib.crc32(p.data, c)
                if p.ends:
                    rows.append(piece(p))
                    n = c = 0
            yield pa.RecordBatch.from_pylist([*rows, piece(probe.Part())], schema=kind)

    ship(index.sparkSession)
    return spread_points(index).mapInArrow(run, "file_id long, point_no long, seq long, n long, crc long, ends boolean, footer_crc long, isize long")


def _fold(t: pa.Table) -> pa.Table:
    """Checksums of one file's pieces in order, folded to one row per member."""
    t = t.sort_by([("point_no", "ascending"), ("seq", "ascending")])
    rows, crc, n, no = [], 0, 0, 0
    for r in t.to_pylist():
        crc, n = crc_.combine(crc, r["crc"], r["n"]), n + r["n"]
        if r["ends"]:
            rows.append({"file_id": r["file_id"], "member_no": no, "n": n, "crc32": crc, "ok": crc == r["footer_crc"] and n & 0xFFFFFFFF == r["isize"]})
            crc, n, no = 0, 0, no + 1
    return pa.Table.from_pylist(rows, schema=pa.schema([("file_id", pa.int64()), ("member_no", pa.int64()), ("n", pa.int64()), ("crc32", pa.int64()), ("ok", pa.bool_())]))


def verify(index: DataFrame, strict: bool = False) -> DataFrame:
    """(file_id, member_no, n, crc32, ok): combined checksums against the members' footers; rows of a few numbers per piece meet per file."""
    out = checksums(index).groupBy("file_id").applyInArrow(_fold, "file_id long, member_no long, n long, crc32 long, ok boolean")
    if strict and (bad := out.where(~F.col("ok")).first()):
        raise ChecksumMismatch(f"member {bad.member_no} of file {bad.file_id}")
    return out


#: Requests of a point that one task answers; a point in greater demand is inflated by several.
REQUESTS = 50_000


def read_ranges(requests: DataFrame, index: DataFrame, spacing: int) -> DataFrame:
    """(file_id, request_id, bytes) for requests (file_id, request_id, offset, len).

    Points and requests meet in buckets of ``spacing`` bytes (an equi-join), each point with requests is inflated once, or once for every
    ``REQUESTS`` of them, and the parts of a request that spans points are put together again.
    """
    ship(index.sparkSession)
    buckets = lambda a, b: F.explode(F.sequence(F.floor(a / spacing), F.floor((b - 1) / spacing)))
    asked = requests.where("len > 0").withColumn("bucket", buckets(F.col("offset"), F.col("offset") + F.col("len")))
    points = index.where("out_len > 0").select("file_id", "point_no", "out_start", "out_len").withColumn("bucket", buckets(F.col("out_start"), F.col("out_start") + F.col("out_len")))
    hit = asked.join(points, ["file_id", "bucket"]).where((F.col("offset") < F.col("out_start") + F.col("out_len")) & (F.col("out_start") < F.col("offset") + F.col("len")))
    hit = materialize(hit.select("file_id", "point_no", "request_id", "offset", "len").distinct(), "asked")
    demand = hit.groupBy("file_id", "point_no").agg(F.count(F.lit(1)).alias("n")).withColumn("salts", F.ceil(F.col("n") / REQUESTS).cast("int")).drop("n")
    salted = hit.join(demand, ["file_id", "point_no"]).withColumn("salt", F.pmod(F.xxhash64("request_id", "offset"), F.col("salts")).cast("int"))
    grouped = salted.groupBy("file_id", "point_no", "salt").agg(F.array_sort(F.collect_list(F.struct("offset", "len", "request_id"))).alias("asks"))
    kind = pa.schema([("file_id", pa.int64()), ("request_id", pa.int64()), ("part", pa.int64()), ("bytes", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for r in _rows(batches):
            # Requests in order of their offset: bytes before the first that is still open are dropped as the point goes by.
            asks, rows, open_, base, held = iter(r["asks"]), [], [], r["out_start"], b""
            nxt = next(asks, None)
            for data in point_bytes(r):
                held += data
                while nxt is not None and nxt["offset"] < base + len(held):
                    open_.append(nxt)
                    nxt = next(asks, None)
                left = []
                for q in open_:
                    if q["offset"] + q["len"] <= base + len(held):
                        rows.append(_part(r, q, held, base))
                    else:
                        left.append(q)
                open_ = left
                keep = min([max(base, q["offset"]) for q in open_], default=base + len(held))
                held, base = held[keep - base :], keep
                if rows:
                    yield pa.RecordBatch.from_pylist(rows, schema=kind)
                    rows = []
                if nxt is None and not open_:
                    break
            if open_:
                yield pa.RecordBatch.from_pylist([_part(r, q, held, base) for q in open_], schema=kind)

    wanted = materialize(grouped.join(index, ["file_id", "point_no"]), "wanted")
    parts = spread_points(wanted).mapInArrow(run, "file_id long, request_id long, part long, bytes binary")
    whole = parts.groupBy("file_id", "request_id").agg(F.array_sort(F.collect_list(F.struct("part", "bytes"))).alias("p"))
    return whole.select("file_id", "request_id", F.when(F.size("p") == 1, F.col("p")[0]["bytes"]).otherwise(F.unhex(F.array_join(F.transform("p", lambda x: F.hex(x["bytes"])), ""))).alias("bytes"))


def _part(r: dict, q: dict, held: bytes, base: int) -> dict:
    return {"file_id": r["file_id"], "request_id": q["request_id"], "part": r["point_no"], "bytes": held[max(0, q["offset"] - base) : q["offset"] + q["len"] - base]}


def points_upto(index: DataFrame, upto: int) -> DataFrame:
    return index.where(F.col("out_start") < upto)


