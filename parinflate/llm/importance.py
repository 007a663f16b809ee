"""Quality classifier by importance resampling.

Two generative models over hashed n-grams (words and punctuation runs, alone and in pairs; a pair of equal tokens is one event of its
own) are counted: one of target text, one of all text. A document's log weight is the log ratio of its probabilities under the two, per
n-gram and for ``SCALE`` n-grams at most: so long texts do not drown the random part and short ones keep the little evidence that they
have. A Gumbel variate from a hash of the row and a seed is added, and the k largest keys are the sample: k draws without
replacement, each in proportion to the weights that are left.

``k`` is a share of the rows if one is given. Else it is how many rows the labels say are like the target: the labelled rows are cut
into ``BINS`` classes of log weight, each class has a share of target rows, and the classes of all rows add up. Three standard errors
and what one labelled row stands for are added, so the estimate errs towards keeping.

The counts cover every text once, however many rows hold it, so copies do not lower their own weight: rows are counted by how many
hold their text and each count is divided by that number, which is exact. The target is the labelled rows of quality 1, at most about
``MOST_LABELLED`` of them by hash; its texts count once too. Only the two tables of ``BUCKETS`` counts, the classes and counts of keys
reach the driver.

Defined results: null or empty texts have weight 0; rows that tie on the key at the cut stay together; a label that is null is no
label; without target rows all weights are 0 and every row stays. Columns beyond id and text are not read.
"""

from __future__ import annotations

import math
import re
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from parinflate.llm.tables import Bounded, claim
from parinflate.runtime import materialize, ship, table

BUCKETS = 10_000
MOST_LABELLED = 200_000
#: N-grams that a log weight counts for at most; classes of log weight by which labels are carried over to all rows.
SCALE, BINS = 40, 64
SEED = 77
#: Bytes of a worker's table of token hashes.
CACHE = 24 << 20
#: Tables of counts that a task holds before it hands them on.
MOST_HELD = 128
_tokens = re.compile(r"\w+|[^\w\s]+").findall
_K1, _K2, _REPEAT = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x5BD1E995)
#: Packed token hashes of blank-delimited pieces.
_hashes = Bounded(lambda piece: np.array([zlib.crc32(x.encode()) for x in _tokens(piece)], np.uint32).tobytes(), lambda piece, v: 4 * len(piece) + len(v) + 220, CACHE)


def grams(text: str | None) -> np.ndarray:
    """Buckets of the n-grams of a text, lower-cased."""
    if not text:
        return np.empty(0, np.int64)
    q = np.frombuffer(b"".join(map(_hashes.__getitem__, text.lower().split())), np.uint32).astype(np.uint64)
    pair = q[:-1] * _K1 + q[1:] * _K2
    pair ^= pair >> np.uint64(29)
    pair[q[:-1] == q[1:]] = _REPEAT
    return (np.concatenate([q, pair]) % np.uint64(BUCKETS)).astype(np.int64)


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(bucket, copies, raw, target) counts of this task's rows: raw by rows that hold the text, target by target rows that hold it."""
    claim("importance", _hashes.clear)
    raw: dict[int, np.ndarray] = {}
    target: dict[int, np.ndarray] = {}

    def rows() -> Iterator[pa.RecordBatch]:
        none = np.zeros(BUCKETS, np.int64)
        for copies in sorted(raw.keys() | target.keys()):
            r, t = raw.get(copies, none), target.get(copies, none)
            at = np.flatnonzero(r + t)
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(np.full(len(at), copies)), pa.array(r[at]), pa.array(t[at])], ["bucket", "copies", "raw", "target"])
        raw.clear()
        target.clear()

    for batch in batches:
        for text, good, n, m in zip(*batch.columns, strict=True):
            b = np.bincount(grams(text.as_py()), minlength=BUCKETS)
            for counts, copies in ((raw, n.as_py()), (target, m.as_py() if good.as_py() else 0)):
                if copies:
                    if copies in counts:
                        counts[copies] += b
                    else:
                        counts[copies] = b
        if len(raw) + len(target) > MOST_HELD:
            yield from rows()
    yield from rows()


def sampled(labels: DataFrame, most: int, *key: str) -> DataFrame:
    """About ``most`` rows of ``labels`` at most, by a hash of ``key``."""
    n = labels.count()
    return labels if n <= most else labels.where(F.pmod(F.xxhash64(*key, F.lit(SEED)), F.lit(1 << 30)) < int((1 << 30) * most / n))


def _target(labels: DataFrame, most: int) -> DataFrame:
    return sampled(labels.where(F.col("quality") == 1).select(F.col("doc_id").alias("good_id")).where("good_id IS NOT NULL").distinct(), most, "good_id")


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", most: int = MOST_LABELLED) -> np.ndarray:
    """Log ratio of target to raw probability by bucket; zeros without a target."""
    ship(docs.sparkSession)
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).where("text <> ''")
    flagged = texts.join(F.broadcast(_target(labels, most)), F.col("id") == F.col("good_id"), "left").select("text", F.col("good_id").isNotNull().alias("good"))
    flagged = flagged.withColumn("digest", F.unhex(F.md5("text")))
    copied = flagged.groupBy("digest").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("good").cast("long")).alias("m")).where("n > 1")
    # The digests of copied texts are few and thin: Spark broadcasts them, or joins by digest where they are many.
    once = flagged.join(materialize(copied, "copied"), "digest", "left").select("text", "good", F.coalesce("n", F.lit(1)).alias("n"), F.coalesce("m", F.lit(1)).alias("m"))
    counted = once.mapInArrow(_count, "bucket long, copies long, raw long, target long").groupBy("bucket", "copies").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target"))
    rows = counted.groupBy("bucket").agg(F.sum(F.expr("raw div copies")).alias("raw"), F.sum(F.expr("target div copies")).alias("target")).collect()
    raw, target = np.zeros(BUCKETS), np.zeros(BUCKETS)
    for r in rows:
        raw[r.bucket], target[r.bucket] = r.raw, r.target
    if not target.sum():
        return np.zeros(BUCKETS)
    return np.log((target + 1) / (target.sum() + BUCKETS)) - np.log((raw + 1) / (raw.sum() + BUCKETS))


def log_weight(text: str | None, ratios: np.ndarray, scale: int = SCALE) -> float:
    g = grams(text)
    return float(ratios[g].mean()) * min(len(g), scale) if len(g) else 0.0


def _scorer(ratios: np.ndarray, scale: int = SCALE) -> Callable:
    def score(texts: pa.Array) -> pa.Array:
        claim("importance", _hashes.clear)
        return pa.array([log_weight(t.as_py(), ratios, scale) for t in texts], pa.float64())

    return F.arrow_udf(score, T.DoubleType())


def gumbel(id_: Column, text: Column, seed: int = SEED) -> Column:
    """A Gumbel variate drawn by a hash of the row."""
    u = (F.pmod(F.xxhash64(id_, text, F.lit(seed)), F.lit(1 << 52)).cast("double") + 0.5) / float(1 << 52)
    return -F.log(-F.log(u))


def kth_largest(keys: DataFrame, col: str, k: int, bins: int = 1024) -> float:
    """The k-th largest value of a column, exactly: each pass counts the values of the interval that holds it by bins."""
    lo, hi = keys.agg(F.min(col), F.max(col)).first()
    if lo is None or k <= 0:
        return math.inf
    above = 0
    while lo < hi:
        width = (hi - lo) / bins
        if lo + width == lo:
            break
        bin_ = F.least(F.lit(bins - 1), F.floor((F.col(col) - lo) / width))
        found = keys.where(F.col(col).between(lo, hi)).groupBy(bin_.alias("bin")).agg(F.count(F.lit(1)).alias("n"), F.min(col).alias("a"), F.max(col).alias("b")).orderBy(F.desc("bin")).collect()
        for r in found:
            if above + r.n >= k:
                lo, hi = r.a, r.b
                break
            above += r.n
        else:
            return lo
    return lo


def like_target(keys: DataFrame, labels: DataFrame, most: int = MOST_LABELLED, bins: int = BINS) -> int | None:
    """How many rows of ``keys`` (id, log_weight) are like the target, by the labels' shares in classes of log weight; None without labels of both kinds."""
    known = labels.where("quality IN (0, 1) AND doc_id IS NOT NULL").groupBy(F.col("doc_id").alias("known_id")).agg(F.max("quality").alias("quality"))
    marked = materialize(keys.join(F.broadcast(sampled(known, most, "known_id")), F.col("id") == F.col("known_id")).select("log_weight", "quality"), "marked")
    if marked.select("quality").distinct().count() < 2:
        return None
    edges = sorted(set(marked.agg(F.percentile_approx("log_weight", [k / bins for k in range(1, bins)], 100_000)).first()[0]))
    class_ = F.aggregate(F.lit(edges), F.lit(0), lambda n, e: n + (F.col("log_weight") > e).cast("int")).alias("class")
    known_by = {r["class"]: (r.n, r.good / r.n) for r in marked.groupBy(class_).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("quality").cast("long")).alias("good")).collect()}
    whole = variance = rows = 0.0
    for r in keys.groupBy(class_).agg(F.count(F.lit(1)).alias("n")).collect():
        n, p = known_by.get(r["class"], (1, 1.0))
        rows, whole, variance = rows + r.n, whole + r.n * p, variance + r.n**2 * p * (1 - p) / n
    return math.ceil(whole + 3 * math.sqrt(variance) + rows / sum(n for n, _ in known_by.values()))


class Resampler:
    """Fitted models, the scored rows and the cut of the sample of ``docs``.

    Texts are read twice, to count and to score. With ``whole`` the scored rows are written with all their columns, so that the sample
    is read from there; otherwise only (id, log_weight, key) are.
    """

    def __init__(self, docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", most: int = MOST_LABELLED, share: float | None = None, seed: int = SEED, scale: int = SCALE, whole: bool = False):
        self.columns = docs.columns
        own = "_importance"
        while any(c.lower().startswith(own) for c in docs.columns):
            own += "_"
        self.weight, self.key = f"{own}_weight", f"{own}_key"
        self.ratios = fit(docs, labels, id_col, text_col, most)
        named = docs.withColumn(self.weight, _scorer(self.ratios, scale)(F.col(text_col).cast("string")))
        named = named.withColumn(self.key, F.col(self.weight) + gumbel(F.col(id_col), F.col(text_col), seed))
        self.rows = materialize(named if whole else named.select(F.col(id_col).alias("id"), self.weight, self.key), "importance")
        self.keys = self.rows.select((F.col(id_col) if whole else F.col("id")).alias("id"), F.col(self.weight).alias("log_weight"), F.col(self.key).alias("key"))
        n = self.keys.count()
        k = math.ceil(share * n) if share is not None else like_target(self.keys, labels, most) if self.ratios.any() else None
        self.k = n if k is None else min(n, k)
        self.cut = kth_largest(self.keys, "key", self.k)

    def marked(self) -> DataFrame:
        """(id, log_weight, key, kept) of every row."""
        return self.keys.withColumn("kept", F.col("key") >= self.cut)

    def sample(self) -> DataFrame:
        """The rows in the sample with their columns (``whole``)."""
        return self.rows.where(F.col(self.key) >= self.cut).select(*self.columns)


def sample(docs: DataFrame, labels: DataFrame, **how) -> DataFrame:
    """The rows of ``docs`` in the sample."""
    return Resampler(docs, labels, whole=True, **how).sample()


def op6_quality_importance(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = Resampler(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")).marked()
    return found.select(F.col("id").alias("doc_id"), "log_weight", "key", "kept")
