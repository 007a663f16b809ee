"""Streams: archives as they arrive, windows over access traces, replay with state."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceStreamArrowWriter, WriterCommitMessage
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import StructType

from parinflate.functions.sqlapi import gzip_decompress
from parinflate.plans.prefetch import ChunkCache, replay_one
from parinflate.runtime import scratch_path, ship
from parinflate.sources.gzip_source import serial
from parinflate.sources.writers import open_out


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream."""
    path = f"{sf_dir}/events.parquet"
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    one = p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isFile()  # streams read folders
    reader = spark.readStream.schema(spark.read.parquet(path).schema)
    return reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir) if one else reader.parquet(path)


def micros(ts: str) -> Column:
    """Microseconds since 1970 of a timestamp, in no time zone."""
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', CAST({ts} AS TIMESTAMP_NTZ))")


class _Batches(DataSourceStreamArrowWriter):
    """Each task writes its rows as a Parquet file; a batch counts once its list of files is written."""

    def __init__(self, path: str):
        self.path = path

    def write(self, iterator: Iterator[pa.RecordBatch]) -> WriterCommitMessage:
        name, out, file = f"{self.path}/rows/{uuid.uuid4().hex}.parquet", None, None
        for batch in iterator:
            if batch.num_rows:
                if out is None:
                    file = open_out(name)
                    out = pq.ParquetWriter(file, batch.schema, compression="zstd")
                out.write_batch(batch)
        if out is None:
            return Batch("")
        out.close()
        file.close()
        return Batch(name)

    def commit(self, messages: list[WriterCommitMessage | None], batchId: int) -> None:
        f = open_out(f"{self.path}/batches/{batchId:09d}")
        f.write("".join(f"{batchId} {m.name}\n" for m in messages if m is not None).encode() or f"{batchId} \n".encode())
        f.close()

    def abort(self, messages: list[WriterCommitMessage | None], batchId: int) -> None:
        """Files of no list are not read."""


@dataclass
class Batch(WriterCommitMessage):
    name: str


class BatchFiles(DataSource):
    @classmethod
    def name(cls) -> str:
        return "parinflate_batches"

    def streamWriter(self, schema: StructType, overwrite: bool) -> DataSourceStreamArrowWriter:
        return _Batches(self.options["path"])


def run(df: DataFrame, mode: str, name: str) -> DataFrame:
    """All that is there now, written by executors to the shared folder: of complete batches the last one, otherwise all. The driver sees names of files only.

    Such a sink takes no updates; they go through a memory sink, whose rows, one per key and batch, the driver holds.
    """
    spark = df.sparkSession
    if mode == "update":
        spark.catalog.dropTempView(name)
        q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", scratch_path(spark, f"stream-{name}")).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.table(name)
    ship(spark)
    spark.dataSource.register(BatchFiles)
    path = scratch_path(spark, f"sink-{name}")
    q = df.writeStream.outputMode(mode).format("parinflate_batches").option("checkpointLocation", scratch_path(spark, f"stream-{name}")).trigger(availableNow=True).start(path)
    q.awaitTermination()
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}/batches")
    any_ = p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)
    said = [r.value.split(" ", 1) for r in spark.read.text(f"{path}/batches").collect()] if any_ else []
    newest = max((int(k) for k, _ in said), default=-1)
    files = [f for k, f in said if f and (mode != "complete" or int(k) == newest)]
    return spark.read.schema(df.schema).parquet(*files) if files else spark.createDataFrame([], df.schema)


def tumbling(stream: DataFrame, width: str = "1 hour") -> DataFrame:
    w = F.window("ts", width)
    return stream.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(stream: DataFrame, width: str = "2 hours", step: str = "1 hour") -> DataFrame:
    return stream.groupBy(F.window("ts", width, step).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return stream.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def on_time(stream: DataFrame, delay: str = "10 minutes", width: str = "1 hour") -> DataFrame:
    """Windows that the watermark has closed; rows behind it are dropped."""
    return stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay).groupBy(F.window("ts", width).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


def decompress_new(spark: SparkSession, folder: str) -> DataFrame:
    """(path, content) of small archives as they arrive, each in a cell; see :func:`new_lines` for large ones."""
    ship(spark)
    files = spark.readStream.format("binaryFile").schema("path string, modificationTime timestamp, length long, content binary").load(folder)
    return files.select("path", gzip_decompress("content").alias("content"))


def new_lines(spark: SparkSession, folder: str, files_per_batch: int = 1000) -> DataFrame:
    """(path, out_pos, line) of archives as they arrive: a stream of names, of which each task inflates its own piece by piece."""
    ship(spark)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path in batch.column(0).to_pylist():
                at, rest = 0, b""
                for data in serial(path):
                    *whole, rest = (rest + data).split(b"\n")
                    if whole:
                        yield _line_batch(path, at, whole)
                        at += sum(map(len, whole)) + len(whole)
                if rest:
                    yield _line_batch(path, at, [rest])

    # The content is not selected, so it is not read.
    files = spark.readStream.format("binaryFile").schema("path string, modificationTime timestamp, length long, content binary").option("maxFilesPerTrigger", files_per_batch).load(folder)
    return files.select("path").repartition(spark.sparkContext.defaultParallelism, "path").mapInArrow(run, "path string, out_pos long, line string")


def _line_batch(path: str, at: int, lines: list[bytes]) -> pa.RecordBatch:
    pos = []
    for x in lines:
        pos.append(at)
        at += len(x) + 1
    return pa.RecordBatch.from_arrays([pa.array([path] * len(lines)), pa.array(pos, pa.int64()), pa.array([x.decode("utf-8", "replace") for x in lines])], ["path", "out_pos", "line"])


def trace_files(spark: SparkSession, trace: DataFrame, files: int) -> DataFrame:
    """A trace (reader_id, seq, point_no) as a stream of ``files`` files in order of seq, one to a micro-batch."""
    path = scratch_path(spark, "trace")
    lo, hi = trace.agg(F.min("seq"), F.max("seq")).first()
    for k in range(files if lo is not None else 0):
        a, b = lo + (hi - lo + 1) * k // files, lo + (hi - lo + 1) * (k + 1) // files
        trace.where((F.col("seq") >= a) & (F.col("seq") < b)).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(trace.schema).option("maxFilesPerTrigger", 1).parquet(path)


def replay(stream: DataFrame, strategy: str = "adaptive", degree: int = 4) -> DataFrame:
    """Counters per reader, with the history and the caches kept as state between batches; the stream has reader_id, seq, point_no."""
    ship(stream.sparkSession)

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        history, acc, pre, hits, misses = state.get if state.exists else ([], [], [], 0, 0)
        history, cache = list(history), ChunkCache(1, 2 * degree)
        for c in acc:
            cache.access[c] = 0
        for c in pre:
            cache.prefetch[c] = 0
        trace = pd.concat(list(frames)).sort_values("seq")["point_no"].tolist()
        got = replay_one(trace, strategy, degree, history=history, cache=cache)
        hits, misses = hits + got["hits"], misses + got["misses"]
        state.update((history[-2 * degree :], list(cache.access), list(cache.prefetch), hits, misses))
        yield pd.DataFrame([{"reader_id": key[0], "hits": hits, "misses": misses}])

    return stream.groupBy("reader_id").applyInPandasWithState(step, "reader_id long, hits long, misses long", "history array<long>, acc array<long>, pre array<long>, hits long, misses long", "update", GroupStateTimeout.NoTimeout)
