"""Toxicity: a counterfactual-regularised classifier.

A logistic model over the presence of words and of their first letters, and of several different words that share these. Words and prefixes are chosen by counts over the labelled
sample; the model is fitted with a penalty on the change of a sentence's logit when an identity term in it is swapped for another,
which pulls the weights of all identity terms together and so keeps neutral mentions of groups from scoring.

Labels come from at most about ``MOST_LABELLED`` rows by hash, all with crc32 of the id not 2 modulo 4. Only they reach the driver, as
lists of chosen features; scoring reads nothing but texts.

Defined results: null and empty texts get the score of a text without features; rows that repeat get equal scores; without
training rows every score is 0. Columns beyond id and text are not read.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parinflate.llm.importance import sampled
from parinflate.runtime import ship, table

MOST_LABELLED, MOST_FEATURES, THRESHOLD = 20_000, 4096, 0.3
PREFIXES = (3, 4, 5, 7)
#: Several different tokens with a feature are a feature of their own, and so are several among at most so many different tokens each.
DENSE = 60
CACHE = 400_000
#: Identity terms by language, swapped for one another.
IDENTITY = {
    "en": ("women", "men", "muslims", "christians", "jews", "hindus", "gay", "straight", "black", "white", "asian", "immigrants", "disabled", "elderly"),
    "de": ("frauen", "männer", "muslime", "christen", "juden", "schwule", "schwarze", "weiße", "einwanderer", "behinderte"),
    "fr": ("femmes", "hommes", "musulmans", "chrétiens", "juifs", "homosexuels", "noirs", "blancs", "immigrés", "handicapés"),
    "es": ("mujeres", "hombres", "musulmanes", "cristianos", "judíos", "homosexuales", "negros", "blancos", "inmigrantes", "discapacitados"),
}
_edges = re.compile(r"^\W+|\W+$")


def features(token: str) -> tuple[str, ...]:
    """Features of one blank-delimited, lower-cased token: the word and its first letters."""
    word = _edges.sub("", token)
    return (word, *(f"{word[:k]}-" for k in PREFIXES if len(word) > k)) if word else ()


def tokens(text: str | None) -> set[str]:
    return set(text.lower().split()) if text else set()


def present(found: Iterator[str], n_tokens: int) -> set[str]:
    """Features of a text from those of its different tokens."""
    count = Counter(found)
    more = {f for f, n in count.items() if n > 1}
    return {*count, *(f"{f}|2" for f in more), *(f"{f}|d" for f in more if count[f] * DENSE >= n_tokens)}


def _counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(feature, toxic, clean): documents of this task with each feature; a full table is handed on."""
    found = {1: Counter(), 0: Counter()}

    def flush() -> pa.RecordBatch:
        names = list(found[1].keys() | found[0].keys())
        out = pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array([found[1][x] for x in names], pa.int64()), pa.array([found[0][x] for x in names], pa.int64())], ["feature", "toxic", "clean"])
        found[1].clear()
        found[0].clear()
        return out

    for batch in batches:
        for text, y in zip(batch.column(0), batch.column(1), strict=True):
            ts = tokens(text.as_py())
            found[y.as_py()].update(present((f for t in ts for f in features(t)), len(ts)))
            if len(found[0]) + len(found[1]) > CACHE:
                yield flush()
    yield flush()


class _Hits(dict):
    """Features of a token that the chosen ones are made of; most tokens have none."""

    def __init__(self, chosen: dict[str, int]):
        self.chosen, self.parts = chosen, {f[:-2] if f[-2:] in ("|2", "|d") else f for f in chosen}

    def __missing__(self, token: str) -> tuple[str, ...]:
        if len(self) >= CACHE:
            self.clear()
        v = self[token] = tuple(f for f in features(token) if f in self.parts)
        return v

    def of(self, text: str | None) -> list[int]:
        return self.of_tokens(tokens(text))

    def of_tokens(self, ts: set[str]) -> list[int]:
        found = [f for hit in filter(None, map(self.__getitem__, ts)) for f in hit]
        return sorted(self.chosen[f] for f in present(found, len(ts)) if f in self.chosen) if found else []


def swaps(text: str | None, hits: _Hits, terms: dict[str, tuple[str, ...]] = IDENTITY) -> list[tuple[list[int], list[int]]]:
    """What each swap of an identity term of a text for another of its language takes from the text's features and adds to them."""
    ts = tokens(text)
    words = {t: _edges.sub("", t) for t in ts}
    here = set(words.values())
    if not any(here.intersection(group) for group in terms.values()):
        return []
    old, out = set(hits.of_tokens(ts)), []
    for group in terms.values():
        for a in sorted(here.intersection(group)):
            for b in group:
                if a != b:
                    new = set(hits.of_tokens({t.replace(a, b) if words[t] == a else t for t in ts}))
                    if new != old:
                        out.append((sorted(old - new), sorted(new - old)))
    return out


def _active(chosen: dict[str, int]) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hits = _Hits(chosen)
        kind = pa.list_(pa.struct([("out", pa.list_(pa.int32())), ("new", pa.list_(pa.int32()))]))
        for batch in batches:
            texts = batch.column(0).to_pylist()
            changes = [[{"out": o, "new": n} for o, n in swaps(x, hits)] for x in texts]
            yield pa.RecordBatch.from_arrays([batch.column(1), pa.array([hits.of(x) for x in texts], pa.list_(pa.int32())), pa.array(changes, kind)], ["toxic", "active", "changes"])

    return run


def train(rows: list[tuple[int, list[int]]], n_features: int, pairs: Counter, ridge: float = 1e-2, swap: float = 1.0, steps: int = 400, rate: float = 0.1) -> tuple[np.ndarray, float]:
    """Weights and bias by full-batch gradient steps with momentum and per-weight scale; the swap penalty is the squared change of the logit, weighted by how many swaps of a row's term make this change."""
    y = np.array([r[0] for r in rows], float)
    row = np.repeat(np.arange(len(rows)), [len(r[1]) for r in rows])
    col = np.array([i for r in rows for i in r[1]], int)
    w, b = np.zeros(n_features + 1), math.log((y.sum() + 1) / (len(y) - y.sum() + 1))
    m, v = np.zeros(n_features + 2), np.zeros(n_features + 2)
    change = [(np.array(out, int), np.array(new, int), n / len(rows)) for (out, new), n in sorted(pairs.items())]
    for t in range(1, steps + 1):
        z = b + np.bincount(row, w[:-1][col], minlength=len(rows))
        g = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y) / len(rows)
        gw = np.bincount(col, g[row], minlength=n_features) + ridge * w[:-1] / max(1, len(rows)) ** 0.5
        for out, new, weight in change:
            d = w[new].sum() - w[out].sum()
            gw[new] += swap * weight * d
            gw[out] -= swap * weight * d
        grad = np.concatenate([gw, [0.0, g.sum()]])
        m = 0.9 * m + 0.1 * grad
        v = 0.999 * v + 0.001 * grad**2
        step = rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
        w -= step[:-1]
        b -= step[-1]
    return w[:-1], b


class Model:
    """Chosen features, their weights and the bias."""

    def __init__(self, chosen: dict[str, int], weights: np.ndarray, bias: float):
        self.chosen, self.weights, self.bias = chosen, weights, bias

    def logit(self, active) -> float:
        return self.bias + float(self.weights[active].sum()) if active else self.bias

    def score(self, text: str | None) -> float:
        return 1 / (1 + math.exp(-max(-500.0, min(500.0, self.logit(_Hits(self.chosen).of(text))))))


def choose(counted: DataFrame, n_toxic: int, n_clean: int, most: int = MOST_FEATURES) -> list[str]:
    """Features that toxic rows have more often than clean ones beyond chance: a lower bound of the log ratio, by how much it explains."""
    toxic, clean = F.col("toxic"), F.col("clean")
    bound = F.log((toxic - F.sqrt(toxic) + 0.5) / n_toxic) - F.log((clean + F.sqrt(clean) + 0.5) / n_clean)
    ranked = counted.groupBy("feature").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean")).where("toxic >= 3").withColumn("bound", bound).where(F.col("bound") > math.log(2))
    return [r.feature for r in ranked.orderBy(F.desc(F.col("bound") * toxic), "feature").limit(most).collect()]


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", most: int = MOST_LABELLED) -> Model:
    """Train on labelled rows whose crc32 of the id is not 2 modulo 4."""
    ship(docs.sparkSession)
    usable = labels.where(F.col("toxic").isin(0, 1) & (F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4)) != 2)).select(F.col("doc_id").alias("label_id"), F.col("toxic").cast("int").alias("toxic"))
    taken = sampled(usable, most, "label_id")
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).join(F.broadcast(taken), F.col("id") == F.col("label_id")).select("text", "toxic")
    n = {r.toxic: r["count"] for r in rows.groupBy("toxic").count().collect()}
    if not n.get(1):
        return Model({}, np.zeros(0), -math.inf)
    names = choose(rows.mapInArrow(_counts, "feature string, toxic long, clean long"), n[1], max(1, n.get(0, 0)))
    chosen = {f: i for i, f in enumerate(dict.fromkeys([*names, *(t for group in IDENTITY.values() for t in group)]))}
    active = rows.mapInArrow(_active(chosen), "toxic int, active array<int>, changes array<struct<out: array<int>, new: array<int>>>").collect()
    changes = Counter((tuple(c.out), tuple(c.new)) for r in active for c in r.changes)
    return Model(chosen, *train([(r.toxic, list(r.active)) for r in active], len(chosen), changes))


def _score(model: Model) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hits = _Hits(model.chosen)
        for batch in batches:
            z = np.array([model.logit(hits.of(x.as_py())) for x in batch.column(1)], float)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.where(np.isneginf(z), 0.0, 1 / (1 + np.exp(-np.clip(z, -500, 500)))))], ["id", "score"])

    return run


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, score) of every row."""
    ship(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_score(model), "id long, score double")


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = score(docs, fit(docs, table(spark, sf_dir, "labels")))
    held_out = F.coalesce(F.pmod(F.crc32(F.col("id").cast("string")), F.lit(4)) == 2, F.lit(False))
    return scored.select(F.col("id").alias("doc_id"), held_out.alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
