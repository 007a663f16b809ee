"""Mixing sources to target weights.

Every row gets a hash-random key. Within a source the key space is cut into equal slices (a range partition that needs no sampling,
since keys are uniform), slice sums are prefix-summed over the cluster, and the slice in which a source's budget ends is sorted by
key to find the exact cut. Only thin rows (key, source, size) move, and a row's share is then decided where the row is, by a
table of one row per source.

Sources may be many: they are ranked by a range partition with counts before each part, and targets come from a few passes over the
table of sources, each of which brings one row of sums to the driver. Their tables are broadcast up to a bound on their rows
and joined by shuffle beyond it, where AQE splits a hot source.

Defined results: a null text has size 0 and is never taken; a null source is a source of its own, last in order; rows that tie on
the key (repeated rows) share the part taken at the cut evenly, rounded down; columns beyond id, text and source are not read.
Whole documents are taken but for one per source, at which the budget ends and of which the words up to the budget are taken.
"""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from parinflate.llm.tables import few
from parinflate.runtime import materialize, shuffle_partitions, table

#: Weights by the rank of a source in code point order, repeating.
WEIGHTS = (3, 1, 2)
#: The mix's size as a share of all sizes, and the most epochs of one source.
SHARE, MOST_EPOCHS = Fraction(3, 2), 2
SEED = 20240607


def n_words(text: Column) -> Column:
    """Words are runs of characters other than space and U+0009 to U+000D; null has none."""
    flat = F.trim(F.translate(F.coalesce(text, F.lit("")), "\t\n\x0b\x0c\r", "     "))
    return F.when(flat == "", F.lit(0)).otherwise(F.size(F.split(flat, " +"))).cast("long")


def ranked(sources: DataFrame) -> DataFrame:
    """``sources`` with their rank from 0 by code point (which is the order of UTF-8 bytes), null last: parts of a range partition count on from one another."""
    parts = shuffle_partitions(sources.sparkSession)
    cut = materialize(sources.repartitionByRange(parts, F.col("source").asc_nulls_last()).withColumn("part", F.spark_partition_id()), "ranked")
    before = W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)  # one row per part
    base = cut.groupBy("part").agg(F.count(F.lit(1)).alias("n")).select(F.col("part").alias("b_part"), F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    within = F.row_number().over(W.partitionBy("part").orderBy(F.col("source").asc_nulls_last()))
    return cut.join(F.broadcast(base), F.col("part") == F.col("b_part")).withColumn("rank", (F.col("base") + within - 1).cast("long")).drop("part", "b_part", "base")


def targets(sources: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: Fraction = SHARE, most: int = MOST_EPOCHS) -> DataFrame:
    """(b_source, source_size, target, epochs, rest) from (source, s): weighted parts of ``share`` of everything.

    A source stops at ``most`` times its size and the excess is shared again: sources that stop stay stopped, as what is left
    for the others only grows, so passes end. Sums and comparisons are exact.
    """
    weight = F.element_at(F.lit(list(weights)), (F.col("rank") % len(weights) + 1).cast("int"))
    rows = materialize(ranked(sources).withColumn("w", weight.cast("long")), "sources")
    up, down = share.numerator, share.denominator
    wide = lambda c: c.cast("decimal(38,0)")
    full, rest, unit = F.lit(False), 0, 1
    while True:
        # What is left and the weight it is left to, given who has stopped; a part is rest * w / (down * unit).
        got = rows.agg(F.sum(F.when(~full, wide(F.col("w")))).alias("w"), F.sum(wide(F.col("s"))).alias("s"), F.sum(F.when(full, wide(F.col("s")))).alias("stopped")).first()
        new_rest, new_unit = up * int(got.s or 0) - down * most * int(got.stopped or 0), int(got.w or 0) or 1
        if (new_rest, new_unit) == (rest, unit):
            break
        rest, unit = new_rest, new_unit
        full = wide(F.lit(str(rest))) * wide(F.col("w")) > wide(F.col("s")) * wide(F.lit(str(down * most * unit)))
    part = F.lit(float(rest)) * F.col("w") / F.lit(float(down * unit))
    target = F.when(full, (F.col("s") * most).cast("double")).otherwise(part)
    whole = F.when(full, F.col("s") * most).otherwise(F.round(part).cast("long"))
    epochs = F.when(F.col("s") > 0, F.floor(whole / F.col("s"))).otherwise(F.lit(0)).cast("long")
    return rows.select(F.col("source").alias("b_source"), F.col("s").alias("source_size"), target.alias("target"), epochs.alias("epochs"), F.when(F.col("s") > 0, whole - epochs * F.col("s")).otherwise(F.lit(0)).cast("long").alias("rest"))


def _cuts(keyed: DataFrame, budgets: DataFrame, slices: int) -> DataFrame:
    """(source, cut_key, each) of every source whose last epoch is partial: keys below the cut are taken whole, at it ``each`` words."""
    part = keyed.join(few(budgets), keyed.source.eqNullSafe(budgets.b_source)).where("rest > 0").select("source", "key", "size", "rest")
    part = part.withColumn("slice", F.floor((F.col("key").cast("double") / 2.0**64 + 0.5) * slices).cast("int"))
    sums = part.groupBy("source", "slice").agg(F.sum("size").alias("s"), F.max("rest").alias("rest"))
    run = W.partitionBy("source").orderBy("slice").rowsBetween(W.unboundedPreceding, W.currentRow)
    edge = sums.withColumn("upto", F.sum("s").over(run)).where("upto >= rest AND upto - s < rest").select(F.col("source").alias("e_source"), F.col("slice").alias("e_slice"), (F.col("upto") - F.col("s")).alias("base"))
    edge = few(materialize(edge, "edges"))
    inside = part.join(edge, part.source.eqNullSafe(F.col("e_source")) & (part.slice == F.col("e_slice"))).groupBy("source", "slice", "key").agg(F.sum("size").alias("s"), F.count(F.lit(1)).alias("ties"), F.max("rest").alias("rest"), F.max("base").alias("base"))
    within = W.partitionBy("source", "slice").orderBy("key").rowsBetween(W.unboundedPreceding, W.currentRow)
    at = inside.withColumn("upto", F.col("base") + F.sum("s").over(within)).where("upto >= rest AND upto - s < rest")
    return at.select(F.col("source").alias("c_source"), F.col("key").alias("cut_key"), F.floor((F.col("rest") - (F.col("upto") - F.col("s"))) / F.col("ties")).cast("long").alias("each"))


def plan(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", slices: int = 4096, **how) -> tuple[DataFrame, DataFrame]:
    """The thin table (id, source, size, key) and the mix (one row per source: b_source, source_size, target, epochs, rest, cut_key, each), both written."""
    keyed = df.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), n_words(F.col(text_col)).alias("size"), row_key(F.col(id_col), F.col(text_col)).alias("key"))
    keyed = materialize(keyed, "mix-keys")
    budgets = materialize(targets(keyed.groupBy("source").agg(F.sum("size").alias("s")), **how), "budgets")
    cuts = materialize(_cuts(keyed, budgets, slices), "cuts")
    mix = budgets.join(few(cuts), F.col("b_source").eqNullSafe(F.col("c_source")), "left").drop("c_source").withColumn("each", F.coalesce("each", F.lit(0)))
    return keyed, materialize(mix, "mix")


def row_key(id_: Column, text: Column) -> Column:
    return F.xxhash64(id_, text, F.lit(SEED))


def last_epoch(size: Column, key: Column, cut_key: Column, each: Column) -> Column:
    """Words that a source's last, partial epoch takes of a row."""
    return F.when(key < cut_key, size).when(key == cut_key, F.least(each, size)).otherwise(F.lit(0)).cast("long")


def taken(size: Column, key: Column) -> Column:
    """Words that the mix takes of a row, given the columns of its source's line of the mix."""
    return F.col("epochs") * size + last_epoch(size, key, F.col("cut_key"), F.col("each"))


def op10_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    keyed, mix = plan(table(spark, sf_dir, "documents"))
    joined = keyed.join(few(mix), keyed.source.eqNullSafe(mix.b_source))
    return joined.select(F.col("id").alias("doc_id"), "size", "source_size", "target", taken(F.col("size"), F.col("key")).alias("taken"))


def mixed(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", chars_col: str = "n_chars", **how) -> DataFrame:
    """The rows of the mix with the input's columns: a row once per epoch, and at the cut its text up to the budget's last word."""
    _, mix = plan(df, id_col, text_col, source_col, **how)
    own = "_mix"
    while any(c.lower().startswith(own) for c in df.columns):
        own += "_"
    n_size, n_words_, names = f"{own}_size", f"{own}_words", {c: f"{own}_{c}" for c in mix.columns}
    line = few(mix.withColumnsRenamed(names))
    size = n_words(df[text_col])
    col = lambda c: F.col(names[c])
    part = last_epoch(size, row_key(df[id_col], df[text_col]), col("cut_key"), col("each"))
    words = F.concat(F.array_repeat(size, F.when(size > 0, col("epochs")).otherwise(F.lit(0)).cast("int")), F.array(part))
    out = df.join(line, df[source_col].eqNullSafe(col("b_source"))).withColumn(n_size, size).withColumn(n_words_, F.explode(F.filter(words, lambda w: w > 0)))
    pattern = F.concat(F.lit(r"^((?:[ \t-\r]*+[^ \t-\r]++){"), F.col(n_words_).cast("string"), F.lit(r"}+)"))  # possessive: no recursion on long texts
    cut = F.call_function("regexp_extract", F.col(text_col), pattern, F.lit(1))
    text = F.when(F.col(n_words_) < F.col(n_size), cut).otherwise(F.col(text_col))
    kinds = dict(df.dtypes)
    made = {text_col: text} | ({chars_col: F.when(F.col(n_words_) < F.col(n_size), F.length(cut).cast(kinds[chars_col])).otherwise(F.col(chars_col))} if chars_col in kinds else {})
    return out.select([made[c].alias(c) if c in made else F.col(c) for c in df.columns])
