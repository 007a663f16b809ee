import collections
import hashlib

import corpus_pipeline
from pyspark.sql import functions as F
from test_ops import _links_by_hand, _mix_by_hand
from test_tokens import encoding

from parinflate.llm import importance, mixing
from parinflate.runtime import materialize


def test_stages_equal_brute_force(spark, sf):
    """Each stage's rows, worked out by hand from what it was given."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    # Copies and near copies of some rows, so that every stage has something to do.
    more = docs.where("doc_id % 9 = 0").withColumn("doc_id", F.col("doc_id") + 100_000)
    near = docs.where("doc_id % 11 = 0 AND n_chars > 900").withColumns({"doc_id": F.col("doc_id") + 200_000, "text": F.concat("text", F.lit(" one tail"))})
    docs = materialize(docs.union(more).union(near), "docs")
    columns = docs.columns
    rows = lambda df: sorted((tuple(r) for r in df.collect()), key=str)
    stages = dict(corpus_pipeline.STAGES)

    r = importance.Resampler(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    order = sorted((x.key for x in r.marked().collect()), reverse=True)
    noise = {x.doc_id: x.g for x in docs.select("doc_id", importance.gumbel(F.col("doc_id"), F.col("text")).alias("g")).collect()}
    weight = {x.doc_id: importance.log_weight(x.text, r.ratios) for x in docs.collect()}
    keep = {i for i in noise if weight[i] + noise[i] >= order[r.k - 1]}
    one = materialize(stages["quality_classifier"](spark, docs, sf), "one")
    assert rows(one) == rows(docs.where(F.col("doc_id").isin(list(keep)))) and 0 < len(keep) < docs.count()

    best = {}
    for x in one.collect():
        best[x.text] = max(best.get(x.text, -1), x.doc_id)
    two = materialize(stages["exact_dedup"](spark, one, sf), "two")
    assert rows(two) == rows(one.where(F.col("doc_id").isin(list(best.values())))) and two.count() < one.count()

    root = _links_by_hand([(x.doc_id, x.text) for x in two.collect()], 80)
    three = materialize(stages["near_dedup"](spark, two, sf), "three")
    assert rows(three) == rows(two.where(F.col("doc_id").isin([i for i, c in root.items() if i == c]))) and three.count() < two.count()

    keyed = three.select("doc_id", "source", mixing.n_words(F.col("text")).alias("n"), mixing.row_key(F.col("doc_id"), F.col("text")).alias("key")).collect()
    want = {i: t for i, _, t in _mix_by_hand([(x.doc_id, x.source, x.n, x.key) for x in keyed]) if t}
    text = {x.doc_id: x.text for x in three.collect()}
    four = materialize(stages["mix_sources"](spark, three, sf), "four")
    got = collections.Counter()
    for x in four.collect():
        got[x.doc_id] += len(x.text.encode().split())
        assert text[x.doc_id].startswith(x.text)
    assert got == want and four.columns == three.columns == two.columns == one.columns == columns

    ids = collections.Counter()
    for x in four.collect():
        coded = b"".join(i.to_bytes(4, "little") for i in encoding().encode_ordinary(x.text))
        ids[(x.doc_id, len(coded) // 4, coded, hashlib.sha256(coded).hexdigest(), hashlib.sha256(x.text.encode()).hexdigest())] += 1
    five = stages["byte_bpe"](spark, four, sf).collect()
    assert ids == collections.Counter((x.doc_id, x.n_tokens, bytes(x.ids), x.ids_sha256, x.decoded_sha256) for x in five)


def test_stages_take_odd_rows(spark, sf):
    rows = [(None, None, None, None, None), (1, "", "en", "a", 0), (2, "a b c d e f", "en", None, 11), (2, "a b c d e f", "en", None, 11)]
    odd = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, odd, sf).count() >= 0
        assert stage(spark, odd.limit(0), sf).count() == 0, name
