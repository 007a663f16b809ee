"""As-of and overlap joins by equi-joins on buckets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, by: str, left_on: str, right_on: str, take: list[str]) -> DataFrame:
    """``left`` with the columns ``take`` of the last row of ``right`` (per ``by``) at or before it: one union and one window."""
    a = left.withColumns({"_at": F.col(left_on), "_side": F.lit(1), **{f"_r_{c}": F.lit(None).cast(dict(right.dtypes)[c]) for c in take}})
    b = right.select(by, F.col(right_on).alias("_at"), F.lit(0).alias("_side"), *[F.col(c).alias(f"_r_{c}") for c in take])
    w = Window.partitionBy(by).orderBy("_at", "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = a.unionByName(b, allowMissingColumns=True).withColumns({f"_r_{c}": F.last(f"_r_{c}", ignorenulls=True).over(w) for c in take})
    return both.where("_side = 1").select(*left.columns, *[F.col(f"_r_{c}").alias(c) for c in take])


def overlap(left: DataFrame, right: DataFrame, by: str, left_range: tuple[str, str], right_range: tuple[str, str], bucket: int) -> DataFrame:
    """Pairs of rows whose half-open ranges overlap, met in buckets; each pair once, in the bucket where the later range begins."""
    cut = lambda lo, hi: F.explode(F.sequence(F.floor(F.col(lo) / bucket), F.floor((F.col(hi) - 1) / bucket)))
    (a, b), (c, d) = left_range, right_range
    joined = left.withColumn("_bucket", cut(a, b)).join(right.withColumn("_bucket", cut(c, d)), [by, "_bucket"])
    return joined.where((F.col(a) < F.col(d)) & (F.col(c) < F.col(b)) & (F.col("_bucket") == F.floor(F.greatest(a, c) / bucket))).drop("_bucket")
