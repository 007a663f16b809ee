"""Records from decompressed points: complete lines where the point is, and lines that cross points stitched from their fragments.

Points are inflated twice: first for the fragments at their ends and their counts of newlines, which are thin and written, then for
the lines between, which go on to what reads them and are not written.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from parinflate.operators.index import _rows, point_bytes, spread_points
from parinflate.runtime import materialize, ship

#: Bytes that a line may have: it must fit in a cell, and lines across points in a task.
MAX_LINE = 256 << 20


class LineTooLong(ValueError):
    pass


def _ends(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(file_id, point_no, role, out_pos, line, newlines) of what crosses a point's ends: head and tail, or one middle if it has no newline."""
    for r in _rows(batches):
        head, tail, newlines, size, held = None, [], 0, 0, 0
        for data in point_bytes(r):
            n = data.count(b"\n")
            if n and head is None:
                cut = data.index(b"\n")
                head, tail = b"".join([*tail, data[:cut]]), []
            newlines += n
            size += len(data)
            if n:
                tail, held = [data[data.rindex(b"\n") + 1 :]], 0
            else:
                tail.append(data)
            held += len(tail[-1])
            if held > MAX_LINE:
                raise LineTooLong(f"{r['path']}: a line of more than {MAX_LINE} bytes")
        if not size:
            continue
        rest = b"".join(tail)
        rows = [("middle", r["out_start"], rest)] if head is None else [("head", r["out_start"], head), ("tail", r["out_start"] + size - len(rest), rest)]
        k = len(rows)
        yield pa.RecordBatch.from_arrays([pa.array([r["file_id"]] * k), pa.array([r["point_no"]] * k), pa.array([x[0] for x in rows]), pa.array([x[1] for x in rows]), pa.array([x[2] for x in rows], pa.binary()), pa.array([newlines] * k)], ["file_id", "point_no", "role", "out_pos", "line", "newlines"])


def _between(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(file_id, point_no, seq, out_pos, line) of the lines between two newlines of a point; seq counts from 1 after the head."""
    for r in _rows(batches):
        at, rest, seq = r["out_start"], None, 1
        for data in point_bytes(r):
            if rest is None:  # up to the first newline it is the head
                cut = data.find(b"\n") + 1
                if not cut:
                    at += len(data)
                    continue
                at, rest, data = at + cut, b"", data[cut:]
            data = rest + data if rest else data
            stops = np.flatnonzero(np.frombuffer(data, np.uint8) == 10)
            if len(stops):
                offsets = np.concatenate([[0], stops + 1]).astype(np.int32)
                with_newline = pa.Array.from_buffers(pa.binary(), len(stops), [None, pa.py_buffer(offsets), pa.py_buffer(data)])
                lines_ = pc.binary_slice(with_newline, 0, -1)
                for lo in range(0, len(stops), 20_000):
                    part = lines_.slice(lo, 20_000)
                    n = len(part)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(n, r["file_id"])), pa.array(np.full(n, r["point_no"])), pa.array(np.arange(seq + lo, seq + lo + n)), pa.array(offsets[lo : lo + n].astype(np.int64) + at), part], ["file_id", "point_no", "seq", "out_pos", "line"])
                seq += len(stops)
                at += int(offsets[-1])
                rest = data[int(offsets[-1]) :]
            else:
                rest = data
            if len(rest) > MAX_LINE:
                raise LineTooLong(f"{r['path']}: a line of more than {MAX_LINE} bytes")


def _crossing(ends: DataFrame) -> DataFrame:
    """(file_id, point_no, tail, out_pos, line) of the lines that cross points, from their fragments."""
    w = Window.partitionBy("file_id").orderBy("point_no", "out_pos", F.col("role") == "tail")
    # A head ends the line that is open; a tail opens the next one.
    frag = ends.withColumn("chain", F.sum((F.col("role") == "tail").cast("long")).over(w))
    whole = frag.groupBy("file_id", "chain").agg(F.array_sort(F.collect_list(F.struct("point_no", "out_pos", F.col("role") == "tail", "line"))).alias("p"), F.min(F.struct("point_no", "out_pos", (F.col("role") == "tail").alias("tail"))).alias("a"), F.max((F.col("role") == "head").cast("int")).alias("closed"), F.sum(F.octet_length("line").cast("long")).alias("n"))
    joined = F.when(F.col("n") > MAX_LINE, F.raise_error(F.lit(f"a line of more than {MAX_LINE} bytes")).cast("binary")).otherwise(F.unhex(F.array_join(F.transform("p", lambda x: F.hex(x["line"])), "")))
    return whole.select("file_id", F.col("a.point_no").alias("point_no"), F.col("a.tail").alias("tail"), F.col("a.out_pos").alias("out_pos"), joined.alias("line"), "closed").where((F.col("closed") == 1) | (F.octet_length("line") > 0)).drop("closed")


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(file_id, seq, role, line): the lines inside each cell, and its ends as in :func:`_ends`."""
    for batch in batches:
        for k in range(batch.num_rows):
            r = batch.slice(k, 1).to_pylist()[0]
            found = r["bytes"].split(b"\n")
            roles = ["middle"] if len(found) == 1 else ["head", *["line"] * (len(found) - 2), "tail"]
            for lo in range(0, len(found), 20_000):
                part = found[lo : lo + 20_000]
                n = len(part)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(n, r["file_id"])), pa.array(np.full(n, r["seq"])), pa.array(roles[lo : lo + n]), pa.array(part, pa.binary())], ["file_id", "seq", "role", "line"])


def cell_lines(cells: DataFrame) -> DataFrame:
    """(file_id, line) of the lines of files that lie in cells (file_id, seq, bytes), wherever the cells are cut; no file is put together anywhere. Lines are written once, since cells may be costly to make."""
    ship(cells.sparkSession)
    parts = materialize(cells.select("file_id", "seq", "bytes").mapInArrow(_cut, "file_id long, seq long, role string, line binary"), "cell-lines")
    ends = parts.where("role <> 'line'").select("file_id", F.col("seq").alias("point_no"), F.lit(0).cast("long").alias("out_pos"), "role", "line")
    out = parts.where("role = 'line'").select("file_id", "line").unionByName(_crossing(ends).select("file_id", "line"))
    return out.select("file_id", F.decode("line", "UTF-8").alias("line"))


def lines(index: DataFrame, numbered: bool = False) -> DataFrame:
    """(file_id, out_pos, line) of every line, without its newline; a last line without newline counts if it is not empty.

    With ``numbered`` there is line_no, from counts of newlines per point and the order within. A line longer than ``MAX_LINE`` is an error.
    """
    ship(index.sparkSession)
    points = spread_points(index)
    ends = materialize(points.mapInArrow(_ends, "file_id long, point_no long, role string, out_pos long, line binary, newlines long"), "ends")
    crossing = _crossing(ends)
    between = points.mapInArrow(_between, "file_id long, point_no long, seq long, out_pos long, line binary")
    if not numbered:
        out = between.select("file_id", "out_pos", "line").unionByName(crossing.select("file_id", "out_pos", "line"))
        return out.select("file_id", "out_pos", F.decode("line", "UTF-8").alias("line"))
    # A line's number is how many newlines lie before it: those of earlier points, and of its own those before its place.
    per = ends.groupBy("file_id", "point_no").agg(F.max("newlines").alias("newlines"))
    base = materialize(per.withColumn("base", F.coalesce(F.sum("newlines").over(Window.partitionBy("file_id").orderBy("point_no").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))), "bases")
    out = between.unionByName(crossing.select("file_id", "point_no", F.when(F.col("tail"), F.lit(-1)).otherwise(F.lit(0)).cast("long").alias("seq"), "out_pos", "line"))
    out = out.join(base, ["file_id", "point_no"])
    no = F.col("base") + F.when(F.col("seq") < 0, F.col("newlines")).otherwise(F.col("seq"))
    return out.select("file_id", no.cast("long").alias("line_no"), "out_pos", F.decode("line", "UTF-8").alias("line"))


def json_table(index: DataFrame, schema: str | T.StructType) -> DataFrame:
    """Lines as JSON objects of ``schema``."""
    return lines(index).select(F.from_json("line", schema).alias("r")).select("r.*")


def csv_table(index: DataFrame, schema: str, sep: str = ",") -> DataFrame:
    return lines(index).select(F.from_csv("line", schema, {"sep": sep}).alias("r")).select("r.*")


def count_newlines(index: DataFrame) -> DataFrame:
    """(file_id, newlines, n) without any payload leaving the task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for r in _rows(batches):
            newlines = n = 0
            for data in point_bytes(r):
                newlines += data.count(b"\n")
                n += len(data)
            yield pa.RecordBatch.from_arrays([pa.array([r["file_id"]]), pa.array([newlines]), pa.array([n])], ["file_id", "newlines", "n"])

    ship(index.sparkSession)
    return spread_points(index).mapInArrow(run, "file_id long, newlines long, n long").groupBy("file_id").agg(F.sum("newlines").alias("newlines"), F.sum("n").alias("n"))
