"""Exact dedup by a persistent digest index: a table bucketed and sorted by digest, in a folder that outlives the session.

New rows are reduced to (digest, id), pre-aggregated per digest, anti-joined with the index bucket by bucket and what is new
is appended. Only DataFrame operators run; texts never move, only 32-byte digests do.

Defined results: a null text counts as empty; all empty texts are equal; a digest whose ids are all null has a null keep id and
its rows are kept as one group without a survivor id (``kept`` is true for them, since no id can be told from another); a
repeated row (same id, same text) is kept where its id is the survivor's. Columns of the input other than id and text are not read.
"""

from __future__ import annotations

import atexit
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parinflate.llm.tables import few
from parinflate.runtime import delete_path, materialize, shared_dir, table

_opened: list[tuple[SparkSession, str, str | None]] = []


@atexit.register
def _forget() -> None:
    """Names of this session go; of folders only those that no one asked to keep."""
    for spark, name, path in _opened:
        try:
            if spark.sparkContext._jsc is not None:
                spark.sql(f"DROP TABLE IF EXISTS {name}")
                if path:
                    delete_path(spark, path)
        except Exception:  # the JVM may have gone already
            return


def digests(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, digest) of every row; the digest is the SHA-256 of the text's UTF-8 bytes."""
    return df.select(F.col(id_col).alias("id"), F.unhex(F.sha2(F.coalesce(F.col(text_col), F.lit("")).cast("binary"), 256)).alias("digest"))


class DigestIndex:
    """An index (digest, keep_id) at ``path``, in ``buckets`` buckets by digest, each file sorted by it.

    The folder is the index; a table of this session's catalog is a view of it. Without ``path`` it lies in the shared folder
    and ends with the session. ``add`` appends the digests that the index lacks: for a known digest the row that is already
    there stays the survivor across batches, and within a batch the largest id survives. ``compact`` writes the whole to a new
    folder, one file per bucket. ``buckets`` must be that of the folder's first writer.
    """

    def __init__(self, spark: SparkSession, path: str | None = None, buckets: int = 64):
        self.spark, self.buckets = spark, buckets
        self.path = path or f"{shared_dir(spark)}/parinflate/digest-index-{uuid.uuid4().hex}"
        self.name = self._open(self.path)
        _opened.append((spark, self.name, None if path else self.path))

    def _open(self, path: str) -> str:
        name = f"digest_index_{uuid.uuid4().hex}"
        where = path.replace("'", "''")
        self.spark.sql(f"CREATE TABLE {name} (digest BINARY, keep_id BIGINT) USING parquet CLUSTERED BY (digest) SORTED BY (digest) INTO {self.buckets} BUCKETS LOCATION '{where}'")
        return name

    def read(self) -> DataFrame:
        return self.spark.table(self.name)

    def add(self, batch: DataFrame) -> None:
        """Append what is new in ``batch`` (id, digest), by a sort-merge anti-join; one row per digest leaves each map task."""
        groups = batch.groupBy("digest").agg(F.max("id").cast("long").alias("keep_id"))
        new = groups.hint("merge").join(self.read().select("digest"), "digest", "left_anti")
        new.select("digest", "keep_id").repartition(self.buckets, "digest").sortWithinPartitions("digest").write.insertInto(self.name)

    def compact(self, path: str) -> DigestIndex:
        """The same index at a new ``path`` with one sorted file per bucket; the old folder is left to readers that still have it open."""
        other = DigestIndex(self.spark, path, self.buckets)
        self.read().repartition(self.buckets, "digest").sortWithinPartitions("digest").write.insertInto(other.name)
        return other

    def mark(self, batch: DataFrame) -> DataFrame:
        """(id, digest, keep_id, group_size, kept) for every row of a written batch that has been added; ``group_size`` counts rows of the batch.

        Rows meet a written table of one row per digest, so both sides are shuffled for the join and AQE splits a digest that many rows hold.
        """
        size = batch.groupBy("digest").agg(F.count(F.lit(1)).alias("group_size"))
        groups = materialize(size.hint("merge").join(self.read(), "digest"), "groups")
        joined = batch.join(groups.hint("merge"), "digest", "left")
        return joined.select("id", "digest", "keep_id", "group_size", F.col("id").eqNullSafe(F.col("keep_id")).alias("kept"))


def dedup(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", index: DigestIndex | None = None, buckets: int = 64) -> DataFrame:
    """Add ``df`` to the index (a new one by default) and mark each of its rows; see :class:`DigestIndex`."""
    index = index or DigestIndex(df.sparkSession, buckets=buckets)
    batch = materialize(digests(df, id_col, text_col), "digests")
    index.add(batch)
    return index.mark(batch)


def dedup_in_batches(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", index: DigestIndex | None = None, parts: int = 2) -> DataFrame:
    """All rows of ``df`` through one index in ``parts`` batches, as new data would come: larger ids first, so that what the index has already is what stays."""
    index = index or DigestIndex(df.sparkSession)
    whole = materialize(digests(df, id_col, text_col), "digests")
    lo, hi = whole.agg(F.min("id"), F.max("id")).first()
    cuts = [] if lo is None else [lo + (hi - lo + 1) * k // parts for k in range(1, parts)]
    # Null ids are last: they stay only where no row has an id.
    for a, b in zip([*cuts[::-1], None], [None, *cuts[::-1]], strict=True):
        upper = F.lit(True) if b is None else F.col("id") < b
        index.add(whole.where(F.col("id").isNull() | upper if a is None else (F.col("id") >= a) & upper))
    return index.mark(whole)


def op8_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    marked = dedup_in_batches(table(spark, sf_dir, "documents"))
    return marked.select(F.col("id").alias("doc_id"), "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


OP8_SQL = """
WITH d AS (SELECT doc_id, sha256(coalesce(text, '')) AS h FROM documents),
g AS (SELECT h, max(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY h)
SELECT d.doc_id, g.keep_id, g.group_size, d.doc_id IS NOT DISTINCT FROM g.keep_id AS kept, d.h AS text_sha256 FROM d JOIN g USING (h)
"""


def survivors(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``df`` that stay, with all their columns; of rows that repeat id and text, one stays."""
    own = "_gone"
    while any(c.lower().startswith(own) for c in df.columns):
        own += "_"
    marked = materialize(dedup(df, id_col, text_col), "marked")
    named = lambda rows: rows.select(F.col("id").alias(f"{own}_id"), F.col("digest").alias(f"{own}_digest"))
    gone = named(marked.where(~F.col("kept"))).distinct()
    digest = F.unhex(F.sha2(F.coalesce(df[text_col], F.lit("")).cast("binary"), 256))
    tied = materialize(named(marked.where("kept").groupBy("id", "digest").count().where("count > 1")), "tied")
    on = df[id_col].eqNullSafe(F.col(f"{own}_id")) & (digest == F.col(f"{own}_digest"))
    # Few rows that go are broadcast, so that no text moves; many are shuffled, and AQE can split a row that repeats often.
    single = df.join(few(materialize(gone.union(tied), "gone")), on, "left_anti")
    once = df.join(few(tied), on, "left_semi").dropDuplicates([id_col, text_col])
    return single.unionByName(once)
