"""Window propagation: from tail maps to the 32 KiB before each span, serially per file or by a blocked scan.

A tail map is a function from the window before a span to the window after it. Maps compose, and composition is associative, so a scan
works: compose within groups, walk the groups, then expand within groups.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from parinflate.functions import probe
from parinflate.runtime import materialize, ship

GROUP = 512


def _walk(order: str, start: str | None = None) -> Callable:
    """Over one group sorted by ``order``: the window before each row, from the group's own start (column ``start``) or from zeros."""

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by(order)
        w = (t.column(start)[0].as_py() if start else None) or bytes(probe.WINDOW)
        out = []
        for m in t.column("tail_map"):
            out.append(w)
            w = probe.step(np.frombuffer(m.as_py(), np.uint16), w)
        return pa.table({"file_id": t.column("file_id"), order: t.column(order), "window": pa.array(out, pa.binary())})

    return run


def _compose(t: pa.Table) -> pa.Table:
    t = t.sort_by("start_bit")
    whole = None
    for m in t.column("tail_map"):
        one = np.frombuffer(m.as_py(), np.uint16)
        whole = one if whole is None else probe.compose(whole, one)
    return pa.table({"file_id": t.column("file_id")[:1], "block": t.column("block")[:1], "tail_map": pa.array([whole.tobytes()], pa.binary())})


def propagate(spans: DataFrame, mode: str = "scan", group: int = GROUP) -> DataFrame:
    """(file_id, start_bit, window) of every span; ``spans`` are linked and in a written table."""
    ship(spans.sparkSession)
    thin = spans.select("file_id", "start_bit", "tail_map")
    if mode == "scan":  # one group each: the scan is the walk
        most = spans.groupBy("file_id").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
        mode = "serial" if most <= group else mode
    if mode == "serial":
        return thin.groupBy("file_id").applyInArrow(_walk("start_bit"), "file_id long, start_bit long, window binary")
    places = spans.select("file_id", "start_bit").withColumn("block", F.floor((F.row_number().over(Window.partitionBy("file_id").orderBy("start_bit")) - 1) / group).cast("long"))
    numbered = thin.join(places, ["file_id", "start_bit"])
    whole = numbered.groupBy("file_id", "block").applyInArrow(_compose, "file_id long, block long, tail_map binary")
    entry = materialize(whole.groupBy("file_id").applyInArrow(_walk("block"), "file_id long, block long, window binary").withColumnRenamed("window", "entry"), "entries")
    return numbered.join(entry, ["file_id", "block"]).groupBy("file_id", "block").applyInArrow(_walk("start_bit", "entry"), "file_id long, start_bit long, window binary")


