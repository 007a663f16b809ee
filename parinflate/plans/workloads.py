"""Corpora on the given tables: recipes that turn a table into lines, written as compressed files in the shared folder, with their index."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from parinflate.operators import index
from parinflate.runtime import materialize, scratch_path, ship, table
from parinflate.sources import io, writers

SLOT = 64 << 10
_made: dict[tuple, tuple] = {}


def random_hex(*key: str | Column) -> Column:
    """32 hex digits that SQL engines agree on."""
    return F.md5(F.concat_ws(":", *[(F.col(k) if isinstance(k, str) else k).cast("string") for k in key]))


#: Repeats of experiments on random bits.
SALTS = 12


def random_bytes(salt: int | Column) -> Column:
    """Sixteen random bytes of a line item and salt."""
    return F.unhex(random_hex("l_orderkey", "l_linenumber", salt if isinstance(salt, Column) else F.lit(salt)))


def random_rows(spark: SparkSession, sf_dir: str, salts: int = SALTS) -> DataFrame:
    """(salt, l_orderkey, l_linenumber, b): sixteen random bytes per line item and salt."""
    rows = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return rows.withColumn("b", random_bytes(F.col("salt")))


def _csv(df: DataFrame, *cols: str) -> DataFrame:
    """Fields of plain values joined by commas; null is an empty field, so that later ones keep their place."""
    return df.select(*cols, F.concat_ws(",", *[F.coalesce(F.col(c).cast("string"), F.lit("")) for c in cols]).alias("line"))


def recipe(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, list[str]]:
    """(lines, columns that order them)."""
    t = lambda n: table(spark, sf_dir, n)
    json = lambda df, *cols: df.select(*cols, F.to_json(F.struct(*df.columns), {"ignoreNullFields": "false"}).alias("line"))
    if name == "documents":
        return json(t("documents"), "doc_id"), ["doc_id"]
    if name == "pages":
        return json(t("pages"), "page_id"), ["page_id"]
    if name == "conversations":
        return json(t("conversations"), "conv_id", "turn"), ["conv_id", "turn"]
    if name == "events":
        return json(t("events").withColumn("ts", F.col("ts").cast("string")), "event_id"), ["event_id"]
    if name == "lineitem":
        return _csv(t("lineitem"), "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"), ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]
    if name == "orders":
        return _csv(t("orders"), "o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority"), ["o_orderkey"]
    if name in ("nation", "region"):
        key = "n_nationkey" if name == "nation" else "r_regionkey"
        return json(t(name), key), [key]
    if name == "base64":
        return t("lineitem").select("l_orderkey", "l_linenumber", F.base64(F.unhex(random_hex("l_orderkey", "l_linenumber"))).alias("line")), ["l_orderkey", "l_linenumber"]
    if name == "fastq":
        acgt = F.translate(F.md5(F.col("event_id").cast("string")), "0123456789abcdef", "ACGTACGTACGTACGT")
        quality = F.translate(F.md5(F.concat(F.lit("q"), F.col("event_id").cast("string"))), "0123456789abcdef", "!#$%&()*+-/:;<=>")
        return t("events").select("event_id", F.concat_ws("\n", F.concat(F.lit("@"), F.col("event_id").cast("string")), acgt, F.lit("+"), quality).alias("line")), ["event_id"]
    if name in ("documents_text", "benchmark_text", "conversations_text", "pages_html"):
        source, col = name.split("_")
        key = {"documents": ["doc_id"], "benchmark": ["item_id"], "conversations": ["conv_id", "turn"], "pages": ["page_id"]}[source]
        return t(source).select(*key, F.coalesce(F.col(col), F.lit("")).alias("line")), key
    if name == "nation_name":
        return t("nation").select("n_nationkey", F.col("n_name").alias("line")), ["n_nationkey"]
    raise KeyError(name)


def floats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Slices of the embeddings as raw little-endian 32-bit floats in order of vec_id: binary content that hardly compresses."""
    ship(spark)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [np.asarray(x.values.to_numpy(zero_copy_only=False), "<f4").tobytes() for x in batch.column(0)]
            yield pa.RecordBatch.from_arrays([pa.array(rows, pa.binary())], ["line"])

    e = table(spark, sf_dir, "embeddings").repartitionByRange(8, "vec_id").sortWithinPartitions("vec_id").select("embedding").mapInArrow(run, "line binary")
    raw = materialize(e.withColumn("k", F.monotonically_increasing_id()), "floats")
    return writers.slices(raw, ["k"], slice_bytes=1 << 18, newline=b"")


#: Members of the mixed archive: texts, markup, dialogue, tables as CSV and raw floats.
MEMBERS = ("documents_text", "pages_html", "conversations_text", "benchmark_text", "lineitem", "orders", "embeddings", "nation_name")


def mixed_tar(spark: SparkSession, sf_dir: str, layout: str = "single", level: int = 6, copies: int = 1) -> DataFrame:
    """(file_id, path, size) of one TAR of all ``MEMBERS``; with ``copies`` each of them comes so many times."""
    key = (spark.sparkContext.applicationId, sf_dir, "tar", layout, level, copies)
    if key not in _made:
        members = []
        for c in range(copies):
            for m in MEMBERS:
                parts = floats(spark, sf_dir) if m == "embeddings" else writers.slices(*recipe(spark, sf_dir, m), slice_bytes=1 << 18)
                members.append((f"corpus/{c}/{m}" if copies > 1 else f"corpus/{m}", parts))
        path = f"{scratch_path(spark, 'corpus-tar')}/mixed-{layout}-{level}.tar.gz"
        writers.write(writers.tar_slices(spark, members), path, layout, level)
        _made[key] = (path,)
    return io.archives(spark, _made[key][0])


def saved_index(spark: SparkSession, idx: DataFrame, *key) -> str:
    """Path of ``idx`` saved, once per application and key."""
    key = (spark.sparkContext.applicationId, "saved", *key)
    if key not in _made:
        path = scratch_path(spark, "saved-index")
        index.save(idx, path)
        _made[key] = (path,)
    return _made[key][0]


SCHEMA = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "pages": "page_id long, url string, html string",
    "conversations": "conv_id long, turn long, role string, text string",
    "events": "event_id long, ts string, user_id long, event_type string, value double, props string",
    "lineitem": "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "region": "r_regionkey int, r_name string",
}


def archive(spark: SparkSession, sf_dir: str, name: str, layout: str = "pigz_like", level: int = 6, copies: int = 1) -> DataFrame:
    """(file_id, path, size) of the recipe's file; made once per application."""
    key = (spark.sparkContext.applicationId, sf_dir, name, layout, level, copies)
    if key not in _made:
        lines, order = recipe(spark, sf_dir, name)
        if copies > 1:
            lines = lines.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(copies))))
            order = ["copy", *order]
        path = f"{scratch_path(spark, f'corpus-{name}')}/{layout}-{level}.gz"
        writers.write(writers.slices(lines, order, slice_bytes=1 << 18 if copies == 1 else 4 << 20), path, layout, level)
        _made[key] = (path,)
    return io.archives(spark, _made[key][0])


def archives_by(spark: SparkSession, sf_dir: str, name: str, by: str, layout: str = "single") -> DataFrame:
    """(file_id, path, size) of one file per value of column ``by`` of the recipe's table, in a folder; made once per application."""
    key = (spark.sparkContext.applicationId, sf_dir, name, by, layout)
    if key not in _made:
        lines, order = recipe(spark, sf_dir, name)
        folder = scratch_path(spark, f"corpora-{name}")
        which = table(spark, sf_dir, name).select(*[F.col(o).alias(f"{o}_") for o in order], F.col(by).cast("string").alias("by"))
        on = [F.col(o) == F.col(f"{o}_") for o in order]
        path_ = F.concat(F.lit(f"{folder}/"), F.coalesce("by", F.lit("none")), F.lit(".gz"))
        writers.write_files(writers.slices_by(lines.join(which, on).withColumn("path", path_), "path", order), layout)
        _made[key] = (folder,)
    return io.archives(spark, _made[key][0])


def indexed(spark: SparkSession, sf_dir: str, name: str, layout: str = "pigz_like", level: int = 6, slot: int = SLOT, **how) -> tuple[DataFrame, dict]:
    """(index, counters) of the recipe's file; made once per application."""
    key = (spark.sparkContext.applicationId, sf_dir, name, layout, level, slot, tuple(sorted(how.items())))
    if key not in _made:
        _made[key] = index.build(archive(spark, sf_dir, name, layout, level), slot, **{"group": 16} | how)
    return _made[key]


def trace(spark: SparkSession, sf_dir: str, chunks: int = 8) -> DataFrame:
    """Accesses of readers: (reader_id, seq, point_no) from the events, whose ids follow time."""
    e = table(spark, sf_dir, "events")
    return e.select(F.col("user_id").alias("reader_id"), F.col("event_id").alias("seq"), F.pmod(F.floor(F.abs("value")), F.lit(chunks)).cast("long").alias("point_no"))


def requests(spark: SparkSession, sf_dir: str, records: int, width: int = 25, most: int = 4) -> DataFrame:
    """(request_id, record, n, offset, len) over a file of fixed-width records."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id")
    record, n = F.pmod(F.col("event_id") * 7919 + F.col("user_id"), F.lit(records)), F.pmod(F.col("event_id"), F.lit(most)) + 1
    n = F.least(n, F.lit(records) - record)
    return e.select(F.col("event_id").alias("request_id"), record.alias("record"), n.alias("n"), (record * width).alias("offset"), (n * width).alias("len"))
