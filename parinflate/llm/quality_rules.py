"""Host-level quality rules, by DataFrame functions only.

Each document is measured against document rules. Failures are aggregated by host; a host's failure rate is shrunk towards the
rate of all hosts by a beta prior whose two parameters are fitted to the spread of the hosts' rates (method of moments). A host
whose shrunken rate passes ``MOST_FAILURES`` is rejected, and the verdict joins back to its documents.

Defined results: null or blank texts have no words and fail the base rule; a null host is a host of its own; repeated rows count
each; a table without rows gives none. Columns beyond id, text and host are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from parinflate.llm.tables import few
from parinflate.runtime import materialize, table

LEAST_WORDS, MOST_REPEATED, MOST_SYMBOLS, MOST_DUP_LINES, WORD_LENGTH = 50, 0.5, 0.1, 0.3, (2.0, 14.0)
SYMBOL = r"[#*$%&|<>]"
#: A host is rejected if its shrunken failure rate is above this.
MOST_FAILURES = 0.5


def _bind(value: Column, use) -> Column:
    """``use(value)`` with ``value`` computed once, as the variable of a lambda: an expression inlined into one is computed for every element."""
    return F.element_at(F.transform(F.array(value), use), 1)


def words(text: Column) -> Column:
    """Runs of characters other than space and U+0009 to U+000D."""
    return F.array_remove(F.split(text, r"[ \t-\r]+"), "")


def repeated_words(ws: Column) -> Column:
    """Words inside windows of three words that occur more than once in ``ws``.

    Distinct hashes prove distinct windows, so only texts in which a hash repeats compare windows themselves: sorted with their
    places, equal windows are neighbours, and the places that a repeated window covers are counted once.
    """
    at = lambda w, i, k: F.get(w, i + k)
    places = lambda w: F.sequence(F.lit(0), F.size(w) - 3)

    def exact(w: Column) -> Column:
        windows = F.array_sort(F.transform(places(w), lambda i: F.struct(at(w, i, 0).alias("a"), at(w, i, 1).alias("b"), at(w, i, 2).alias("c"), i.alias("i"))))

        def covered(s: Column) -> Column:
            same = lambda x, y: x["a"].eqNullSafe(y["a"]) & x["b"].eqNullSafe(y["b"]) & x["c"].eqNullSafe(y["c"])
            hit = F.filter(s, lambda x, k: same(x, F.get(s, k - 1)) | same(x, F.get(s, k + 1)))
            return F.size(F.array_distinct(F.flatten(F.transform(hit, lambda x: F.array(x["i"], x["i"] + 1, x["i"] + 2)))))

        return _bind(windows, covered)

    hashes = lambda w: F.transform(places(w), lambda i: F.xxhash64(at(w, i, 0), at(w, i, 1), at(w, i, 2)))
    clear = lambda w: _bind(hashes(w), lambda h: F.size(F.array_distinct(h)) == F.size(h))
    return _bind(ws, lambda w: F.when(F.size(w) < 4, F.lit(0)).when(clear(w), F.lit(0)).otherwise(exact(w)))


def measures(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source") -> DataFrame:
    """(id, host, n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words) of every row."""
    rows = df.select(F.col(id_col).alias("id"), F.col(host_col).alias("host"), F.coalesce(F.col(text_col), F.lit("")).alias("t"))
    text = F.col("t")
    lines = F.filter(F.split(text, "\n"), lambda x: F.btrim(x, F.lit(" \t\x0b\x0c\r")) != "")
    both = _bind(words(text), lambda w: F.struct(F.size(w).alias("n"), F.length(F.array_join(w, "")).alias("chars"), repeated_words(w).alias("r")))
    line = _bind(lines, lambda x: F.struct(F.size(x).alias("n"), F.size(F.array_distinct(x)).alias("d")))
    rows = rows.select("id", "host", both.alias("w"), (F.size(F.split(text, SYMBOL)) - 1).alias("symbols"), line.alias("l"))
    long = lambda c: F.col(c).cast("long") if isinstance(c, str) else c.cast("long")
    return rows.select("id", "host", long("w.n").alias("n_words"), long("w.chars").alias("word_chars"), long("symbols").alias("n_symbols"), long("l.n").alias("n_lines"), long(F.col("l.n") - F.col("l.d")).alias("n_dup_lines"), long("w.r").alias("n_repeat_words"))


def base_failed() -> Column:
    return (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > int(100 * MOST_REPEATED) * F.col("n_words"))


def rule_failed() -> Column:
    """Any document rule: the base rule, symbols, repeated lines, odd word lengths."""
    short, long = (F.col("word_chars") < WORD_LENGTH[0] * F.col("n_words")), (F.col("word_chars") > WORD_LENGTH[1] * F.col("n_words"))
    return base_failed() | (F.col("n_symbols") > MOST_SYMBOLS * F.col("word_chars")) | (F.col("n_dup_lines") > MOST_DUP_LINES * F.col("n_lines")) | short | long


def host_rates(measured: DataFrame) -> DataFrame:
    """(host, docs, failures, rate, host_ok): rates shrunk by the prior that the hosts themselves give."""
    hosts = measured.groupBy("host").agg(F.count(F.lit(1)).alias("docs"), F.sum(rule_failed().cast("long")).alias("failures"))
    share = F.col("failures") / F.col("docs")
    x = hosts.agg(F.avg(share).alias("m"), F.var_samp(share).alias("v"), F.avg(1 / F.col("docs")).alias("inv")).first()  # one row
    alpha, beta = beta_prior(x["m"] or 0.0, x["v"] or 0.0, x["inv"] or 1.0)
    rate = (F.col("failures") + alpha) / (F.col("docs") + alpha + beta)
    return hosts.withColumn("rate", rate).withColumn("host_ok", F.col("rate") <= MOST_FAILURES)


def beta_prior(mean: float, variance: float, inverse_docs: float) -> tuple[float, float]:
    """Parameters from the hosts' rates: the spread of the true rates is what sampling within hosts does not explain."""
    m = min(max(mean, 1e-6), 1 - 1e-6)
    spread = max(variance - m * (1 - m) * inverse_docs, m * (1 - m) * 1e-4)
    weight = max(m * (1 - m) / spread - 1, 1e-3)
    return m * weight, (1 - m) * weight


def judge(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source") -> DataFrame:
    """The measures of every row with base_failed, its host's rate and ``kept``. The thin measures are written once and used twice."""
    measured = materialize(measures(df, id_col, text_col, host_col), "measures")
    # Few hosts are broadcast; where they are many, both sides are shuffled for the join and AQE splits a hot host.
    hosts = few(materialize(host_rates(measured).select(F.col("host").alias("h"), "rate", "host_ok"), "hosts"))
    joined = measured.join(hosts, F.col("host").eqNullSafe(F.col("h")), "left")
    return joined.withColumn("base_failed", base_failed()).withColumn("kept", ~F.col("base_failed") & F.col("host_ok")).drop("h")


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = judge(table(spark, sf_dir, "documents"))
    return found.select(F.col("id").alias("doc_id"), "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


OP7_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, source, coalesce(text, '') AS t FROM documents),
s AS (SELECT rid, doc_id, source, t, [x FOR x IN regexp_split_to_array(t, '[ \t\n\x0B\f\r]+') IF x <> ''] AS w, [x FOR x IN string_split(t, chr(10)) IF regexp_matches(x, '[^ \t\n\x0B\f\r]')] AS l FROM d),
p AS (SELECT rid, i, count(*) OVER (PARTITION BY rid, w[i], w[i + 1], w[i + 2]) AS c FROM (SELECT rid, w, unnest(range(1, len(w) - 1)) AS i FROM s WHERE len(w) >= 3)),
r AS (SELECT rid, count(DISTINCT j) AS n FROM (SELECT rid, unnest([i, i + 1, i + 2]) AS j FROM p WHERE c > 1) GROUP BY rid),
m AS (SELECT doc_id, source, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars, length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS n_symbols, len(l) AS n_lines, len(l) - len(list_distinct(l)) AS n_dup_lines, coalesce(r.n, 0) AS n_repeat_words FROM s LEFT JOIN r USING (rid)),
f AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM m),
g AS (SELECT *, base_failed OR n_symbols > 0.1 * word_chars OR n_dup_lines > 0.3 * n_lines OR word_chars < 2 * n_words OR word_chars > 14 * n_words AS failed FROM f),
h AS (SELECT source, count(*) AS docs, sum(failed::INT) AS failures FROM g GROUP BY source),
a AS (SELECT least(1 - 1e-6, greatest(1e-6, avg(failures / docs))) AS m, coalesce(var_samp(failures / docs), 0) AS v, avg(1 / docs) AS i FROM h),
b AS (SELECT m, greatest(m * (1 - m) / greatest(v - m * (1 - m) * i, m * (1 - m) * 1e-4) - 1, 1e-3) AS k FROM a),
o AS (SELECT source, (failures + m * k) / (docs + k) <= 0.5 AS host_ok FROM h, b)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND host_ok AS kept FROM g JOIN o ON g.source IS NOT DISTINCT FROM o.source
"""
