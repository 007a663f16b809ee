"""Cost and accuracy measures."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

WINDOW = 32768


def bandwidth(n_bytes: int, seconds: list[float]) -> dict[str, float]:
    """MB/s, mean and standard deviation over runs."""
    rates = [n_bytes / 1e6 / s for s in seconds]
    return {"mb_s": statistics.fmean(rates), "sd": statistics.stdev(rates) if len(rates) > 1 else 0.0}


def timed(f: Callable[[], object], runs: int = 1) -> list[float]:
    out = []
    for _ in range(runs):
        t = time.perf_counter()
        f()
        out.append(time.perf_counter() - t)
    return out


def speedup(base: float, seconds: float, cores: int = 1) -> dict[str, float]:
    return {"speedup": base / seconds, "efficiency": base / seconds / cores}


def serial_rate(*rates: float) -> float:
    """Rate of steps that all see the same bytes one after the other."""
    return 1 / sum(1 / r for r in rates)


def ratio(index: DataFrame) -> DataFrame:
    """(file_id, out_len, size, ratio)."""
    return index.groupBy("file_id").agg(F.sum("out_len").alias("out_len"), F.max("size").alias("size")).withColumn("ratio", F.col("out_len") / F.col("size"))


def finder_quality(candidates: DataFrame, blocks: DataFrame) -> DataFrame:
    """(true_positives, false_positives, false_negatives, precision, recall) of candidate ranges [start_bit, last_bit] against blocks (file_id, start_bit)."""
    c, b = candidates.select("file_id", "start_bit", "last_bit"), blocks.select("file_id", F.col("start_bit").alias("true_bit"))
    # A range spans ten bits at most, so an explosion of it is an equi-join.
    wide = c.withColumn("true_bit", F.explode(F.sequence("start_bit", "last_bit")))
    hit = wide.join(b, ["file_id", "true_bit"]).agg(F.count_distinct("file_id", "true_bit").alias("tp"))
    n = c.agg(F.count(F.lit(1)).alias("c")).withColumn("k", F.lit(1)).join(b.agg(F.count(F.lit(1)).alias("b")).withColumn("k", F.lit(1)), "k").join(hit.withColumn("k", F.lit(1)), "k")
    return n.select(F.col("tp").alias("true_positives"), (F.col("c") - F.col("tp")).alias("false_positives"), (F.col("b") - F.col("tp")).alias("false_negatives"), (F.col("tp") / F.col("c")).alias("precision"), (F.col("tp") / F.col("b")).alias("recall"))


def marker_share(linked: DataFrame) -> DataFrame:
    """(spans, out_len, markers, share, anchors): anchors are spans whose last window holds no marker."""
    return linked.agg(F.count(F.lit(1)).alias("spans"), F.sum("out_len").alias("out_len"), F.sum("n_markers").alias("markers"), (F.sum("n_markers") / F.sum("out_len")).alias("share"), F.sum((F.col("out_len") - 1 - F.col("last_marker") >= WINDOW).cast("long")).alias("anchors"))


def amdahl(files: DataFrame, slots_kib: list[int], cores: list[int]) -> DataFrame:
    """Share of the serial window walk in the work of marker replacement over files (name, n_bytes): a walk handles one window of each slot, all cores replace whole slots; the last slot may be short."""
    grid = files.sparkSession.createDataFrame([(s, p) for s in slots_kib for p in cores], "slot_kib long, cores long")
    work = F.col("slot_kib") / (WINDOW // 1024)
    slots = F.ceil(F.col("n_bytes") / (F.col("slot_kib") * 1024)).cast("long")
    serial, parallel = slots * WINDOW, F.col("n_bytes") / F.col("cores")
    return files.crossJoin(F.broadcast(grid)).select("name", "slot_kib", "cores", work.cast("long").alias("less_work"), slots.alias("slots"), F.round(serial / (serial + parallel), 6).alias("serial_share"))


def seek_cost(files: DataFrame, spacings_kib: list[int]) -> DataFrame:
    """Over reads (name, length), at most how many bytes are decoded at each spacing of points, and per byte asked for."""
    grid = files.sparkSession.createDataFrame([(s,) for s in spacings_kib], "spacing_kib long")
    asked = files.groupBy("name").agg(F.count(F.lit(1)).alias("reads"), F.sum("length").alias("asked"))
    most = F.col("reads") * F.col("spacing_kib") * 1024 + F.col("asked")
    return asked.crossJoin(F.broadcast(grid)).select("name", "spacing_kib", "reads", most.alias("most_bytes"), F.round(most / F.col("asked"), 6).alias("amplification"))
