import collections
import html
import math
import re
import zlib
from fractions import Fraction

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from parinflate.llm import components, exact_dedup, html_extract, importance, licenses, minhash_dedup, mixing, quality_rules, toxicity

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls everywhere, empty and blank texts, ties, repeated rows, a long text, a column whose name clashes."""
    long = " ".join(f"w{i % 700}" for i in range(25_000))
    base = " ".join(f"word{i}" for i in range(60))
    rows = [(1, None, "en", "a"), (2, "", "en", "a"), (3, " \t\n", None, None), (4, base, "en", "b"), (5, base, "en", "b"), (5, base, "en", "b"), (6, base + " tail", "en", "b"), (None, base, "en", "b"), (7, long, "en", "c"), (8, "one two", "en", "c"), (9, "One  two", "en", "c"), (10, "%%% ### $$$ " * 30, "en", None)]
    return spark.createDataFrame([(*r, len(r[1] or ""), "x", 0.5) for r in rows], DOCS + ", kept string, score double")


def _sets(rows):
    out = {}
    for i, t in rows:
        w = (t or "").encode().lower().split()
        out[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    return out


def test_exact_dedup(spark, odd):
    got = exact_dedup.dedup(odd).collect()
    assert len(got) == 12
    by = {r.id: (r.keep_id, r.group_size, r.kept) for r in got}
    assert by[4] == (5, 4, False) and by[5] == (5, 4, True) and by[1] == (2, 2, False) and by[None] == (5, 4, False)
    stay = exact_dedup.survivors(odd)
    assert stay.columns == odd.columns and sorted(r.doc_id for r in stay.collect()) == [2, 3, 5, 6, 7, 8, 9, 10]
    assert exact_dedup.dedup(odd.limit(0)).count() == 0


def test_digest_index_keeps_survivors_across_batches(spark, tmp_path):
    index = exact_dedup.DigestIndex(spark, buckets=4)
    a = spark.createDataFrame([(1, "x"), (2, "x"), (3, "y")], "doc_id long, text string")
    b = spark.createDataFrame([(9, "x"), (8, "z")], "doc_id long, text string")
    exact_dedup.dedup(a, index=index)
    got = {r.id: r.kept for r in exact_dedup.dedup(b, index=index).collect()}
    assert got == {9: False, 8: True}
    assert index.compact(f"file://{tmp_path}/again").read().count() == 3


def test_digest_index_outlives_the_session(spark, tmp_path):
    path, rows = f"file://{tmp_path}/it's an index", [(1, "x"), (3, "y"), (None, "z")]
    exact_dedup.dedup(spark.createDataFrame(rows, "doc_id long, text string"), index=exact_dedup.DigestIndex(spark, path, 4))
    other = exact_dedup.DigestIndex(spark.newSession(), path, 4)  # its catalog has no such table
    batch = exact_dedup.digests(other.spark.createDataFrame([(7, "x"), (9, "w")], "doc_id long, text string"))
    plan = batch.groupBy("digest").agg(F.max("id")).hint("merge").join(other.read().select("digest"), "digest", "left_anti")
    assert "SortMergeJoin" in plan._jdf.queryExecution().toString() and "Bucketed: true" in plan._jdf.queryExecution().toString()
    other.add(batch)
    assert {(r.keep_id) for r in other.read().collect()} == {1, 3, None, 9}


def test_exact_dedup_in_batches_equals_one(spark, odd):
    key = lambda df: sorted((r.id is None, r.id, bytes(r.digest), r.keep_id, r.group_size, r.kept) for r in df.collect())
    for parts in (2, 5):
        assert key(exact_dedup.dedup_in_batches(odd, parts=parts)) == key(exact_dedup.dedup(odd))
    assert exact_dedup.dedup_in_batches(odd.limit(0)).count() == 0
    nameless = odd.withColumn("doc_id", F.lit(None).cast("long"))
    assert key(exact_dedup.dedup_in_batches(nameless)) == key(exact_dedup.dedup(nameless)) and exact_dedup.dedup(nameless).where("NOT kept").count() == 0
    clash = odd.withColumns({"_gone_id": F.lit(1), "_gone": F.lit(2), "digest": F.lit("x"), "id": F.lit(3)})
    assert exact_dedup.survivors(clash).columns == clash.columns and exact_dedup.survivors(clash).count() == 8


def _links_by_hand(rows, least):
    """Least id of each row's component, by all pairs that share a shingle."""
    sets = _sets(rows)
    parent = {i: i for i in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    shared = collections.Counter()
    holders = collections.defaultdict(list)
    for i, s in sets.items():
        for z in s:
            holders[z].append(i)
    for v in holders.values():
        v = sorted(v)
        shared.update((v[b], v[a]) for a in range(len(v)) for b in range(a))
    for (a, b), n in shared.items():
        if 100 * n >= least * (len(sets[a]) + len(sets[b]) - n):
            p, q = sorted((root(a), root(b)))
            parent[q] = p
    return {i: root(i) for i in sets}


def test_near_dedup_equals_brute_force(spark, odd, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    base = " ".join(f"t{i}" for i in range(200))
    # A hot group whose members differ from one another at several places, some linked and some not.
    hot = [(100_000 + k, " ".join(w + "x" if (i * 7 + k * 13) % 97 < k % 4 else w for i, w in enumerate(base.split()))) for k in range(60)]
    df = docs.union(spark.createDataFrame(hot, "doc_id long, text string"))
    for least in (80, 85):
        got = {r.id: r.component for r in minhash_dedup.NearDedup(df, least=least).run().collect()}
        assert got == _links_by_hand([(r.doc_id, r.text) for r in df.collect()], least)
    stay = minhash_dedup.survivors(odd)
    assert stay.columns == odd.columns
    assert sorted((r.doc_id is None, r.doc_id) for r in stay.collect()) == sorted((i is None, i) for i in [1, 2, 3, 4, None, 7, 8, 10])


def test_components(spark):
    chain = [(i, i + 1) for i in range(0, 60, 1) if i % 20 != 19] + [(70, 70), (81, 80)]
    got = {r.node: r.component for r in components.components(spark.createDataFrame(chain, "a long, b long")).collect()}
    assert all(got[i] == i // 20 * 20 for i in range(60)) and got[81] == 80 and 70 not in got
    assert components.components(spark.createDataFrame([], "a long, b long")).count() == 0


def _shares(sizes, weights=(3, 1, 2), share=Fraction(3, 2), most=2):
    """Targets by the rule as it is told: whoever is above his limit stops and the rest share again."""
    order = sorted((s for s in sizes if s is not None), key=lambda s: [ord(c) for c in s]) + [None] * (None in sizes)
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    full, rest, left = {}, share * sum(sizes.values()), set(order)
    while left:
        unit = rest / sum(weight[s] for s in left)
        over = {s for s in left if unit * weight[s] > most * sizes[s]}
        if not over:
            return full | {s: unit * weight[s] for s in left}
        full |= {s: Fraction(most * sizes[s]) for s in over}
        rest -= sum(full[s] for s in over)
        left -= over
    return full


def _mix_by_hand(rows):
    """(id, size, taken) of rows (id, source, size, key): whole epochs, then keys in order up to the budget."""
    sizes = collections.Counter()
    for _, s, n, _ in rows:
        sizes[s] += n
    out = []
    for s, goal in _shares(sizes).items():
        mine, budget = [r for r in rows if r[1] == s], int(goal + Fraction(1, 2))
        epochs, rest = divmod(budget, sizes[s]) if sizes[s] else (0, 0)
        by_key = collections.defaultdict(list)
        for r in mine:
            by_key[r[3]].append(r)
        for _, tied in sorted(by_key.items()):
            n = sum(r[2] for r in tied)
            for r in tied:
                more = r[2] if rest > n else min(r[2], rest // len(tied)) if rest > 0 else 0
                out.append((r[0], r[2], epochs * r[2] + (r[2] if rest == n and rest > 0 and len(tied) == 1 else more)))
            rest = max(0, rest - n)
    return sorted(out, key=str)


def test_mixing(spark, odd, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    keyed, mix = mixing.plan(docs)
    by = {r.b_source: r for r in mix.collect()}
    joined = keyed.join(mix, keyed.source.eqNullSafe(mix.b_source)).select("source", "id", "size", "key", mixing.taken(F.col("size"), F.col("key")).alias("taken")).collect()
    # Which rows are taken, row by row.
    assert sorted(((r.id, r["size"], r.taken) for r in joined), key=str) == _mix_by_hand([(r.id, r.source, r["size"], r.key) for r in joined])
    total = collections.Counter()
    for r in joined:
        total[r.source] += r.taken
        assert 0 <= r.taken <= 2 * r["size"]
    assert all(total[s] == round(r.target) for s, r in by.items())
    again = mixing.mixed(docs)
    words = again.select(F.sum(mixing.n_words(F.col("text")))).first()[0]
    assert words == sum(total.values()) and again.columns == docs.columns
    assert mixing.mixed(odd).columns == odd.columns and mixing.mixed(odd).count() > 0
    assert mixing.mixed(odd.limit(0)).count() == 0
    clash = odd.withColumns({c: F.lit(1) for c in ("_mix_size", "_mix_words", "epochs", "target", "key", "size", "b_source")})
    assert mixing.mixed(clash).columns == clash.columns and mixing.mixed(clash).count() == mixing.mixed(odd).count()


@pytest.mark.parametrize("sizes", [{"b": 10, "a": 10, None: 100}, {f"s{k:03}": (k * 37) % 101 for k in range(80)} | {"ü": 5, "z": 9000}, {"only": 7}, {"a": 0, "b": 0}, {None: 3}, {"a": 1, "b": 10**12}])
def test_targets_equal_the_rule(spark, sizes):
    df = spark.createDataFrame(list(sizes.items()), "source string, s long")
    got = {r.b_source: r for r in mixing.targets(df).collect()}
    want = _shares(sizes)
    assert got.keys() == want.keys()
    for s, r in got.items():
        assert r.target == pytest.approx(float(want[s]), rel=1e-12) and r.epochs * sizes[s] + r.rest in (round(want[s]), int(want[s] + Fraction(1, 2)), 0 if not sizes[s] else -1)


def test_quality_rules_equal_brute_force(spark, odd, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "source").union(odd.where("doc_id IS NOT NULL").select("doc_id", "text", "source").withColumn("doc_id", F.col("doc_id") + 500_000).distinct())
    got = {r.id: (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in quality_rules.measures(docs).collect()}
    for r in docs.collect():
        t = r.text or ""
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        n = collections.Counter(zip(w, w[1:], w[2:], strict=False))
        cover = {k + j for k in range(len(w) - 2) if n[(w[k], w[k + 1], w[k + 2])] > 1 for j in range(3)}
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        assert got[r.doc_id] == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(cover)), r.doc_id
    judged = {r.id: (r.base_failed, r.kept) for r in quality_rules.judge(odd).collect()}
    assert judged[1] == (True, False) and judged[7][0] and not judged[6][0]
    assert quality_rules.judge(odd.limit(0)).count() == 0


def test_a_bad_host_goes_and_a_small_one_is_shrunk(spark):
    good = " ".join(f"w{i}" for i in range(80))
    rows = [(i, "x", "bad") for i in range(40)] + [(100 + i, good, "good") for i in range(40)] + [(900, "x", "tiny"), (901, good, "tiny")]
    got = {r.id: r for r in quality_rules.judge(spark.createDataFrame([*rows, (50, good, "bad")], "doc_id long, text string, source string")).collect()}
    assert not got[50].kept and got[100].kept and got[50].rate > 0.5 > got[100].rate


def test_importance(spark, odd, sf):
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    r = importance.Resampler(docs, labels)
    marked = r.marked().collect()
    kept = {x.id for x in marked if x.kept}
    stay = importance.sample(docs, labels)
    assert kept == {x.doc_id for x in stay.collect()} and stay.columns == docs.columns and len(kept) == r.k < len(marked)
    by = {x.doc_id: x.quality for x in labels.collect()}
    assert all(i in kept for i, q in by.items() if q == 1)
    assert sum(i not in kept for i, q in by.items() if q == 0) >= 0.8 * sum(q == 0 for q in by.values())
    keys = sorted((x.key for x in marked), reverse=True)
    for k in (1, 7, len(keys)):
        assert importance.kth_largest(r.marked(), "key", k) == keys[k - 1]
    none = importance.sample(odd, labels.limit(0))
    assert none.count() == odd.count() and none.columns == odd.columns
    clash = odd.withColumns({c: F.lit(1) for c in ("_importance_key", "good_id", "quality", "id", "log_weight", "digest", "class", "n")})
    unsure = labels.union(spark.createDataFrame([(4, None, None), (None, 1, 0)], labels.schema))
    assert importance.sample(clash, unsure).columns == clash.columns


def test_importance_weights_by_hand(spark, sf):
    """Counts, ratios and weights against a plain restatement."""
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    good = {r.doc_id for r in labels.collect() if r.quality == 1}
    raw, target, texts = collections.Counter(), collections.Counter(), {}
    rows = [(r.doc_id, r.text or "") for r in docs.collect()]
    for i, t in rows:
        texts[t] = texts.get(t, False) or i in good
    for t, is_good in texts.items():
        found = collections.Counter(importance.grams(t).tolist())
        raw.update(found)
        target.update(found if is_good else {})
    n, m = sum(raw.values()), sum(target.values())
    ratio = lambda b: math.log((target[b] + 1) / (m + importance.BUCKETS)) - math.log((raw[b] + 1) / (n + importance.BUCKETS))
    got = {r.id: r.log_weight for r in importance.Resampler(docs, labels).marked().collect()}
    for i, t in rows:
        g = importance.grams(t).tolist()
        assert got[i] == pytest.approx(sum(map(ratio, g)) / len(g) * min(len(g), importance.SCALE) if g else 0.0, abs=1e-9)


def test_gumbel_draws_in_proportion_and_by_seed(spark):
    """Over many draws the first of four items is each in proportion to its weight; another seed draws others."""
    w = [0.0, 0.5, 1.0, 2.0]
    items = spark.range(160_000).select((F.col("id") / 4).cast("long").alias("draw"), (F.col("id") % 4).alias("item"), "id")
    weight = F.element_at(F.lit(w), (F.col("item") + 1).cast("int"))
    won = lambda seed: items.withColumn("key", weight + importance.gumbel(F.col("id"), F.lit("t"), seed)).groupBy("draw").agg(F.max_by("item", "key").alias("item"))
    share = {r.item: r.n / 40_000 for r in won(1).groupBy("item").agg(F.count(F.lit(1)).alias("n")).collect()}
    for k, x in enumerate(w):
        assert abs(share[k] - math.exp(x) / sum(map(math.exp, w))) < 0.01
    assert won(1).join(won(2), ["draw", "item"]).count() < 30_000


def test_seeds_give_other_samples_of_the_stated_size(spark, sf):
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    a, b = (importance.Resampler(docs, labels, share=0.4, seed=s) for s in (1, 2))
    ids = [{x.id for x in r.marked().where("kept").collect()} for r in (a, b)]
    assert len(ids[0]) == len(ids[1]) == math.ceil(0.4 * docs.count()) and 10 < len(ids[0] - ids[1])
    # The draw follows the weights: what is kept weighs more on average.
    mean = {x.kept: x.w for x in a.marked().groupBy("kept").agg(F.avg("log_weight").alias("w")).collect()}
    assert mean[True] > mean[False]


def test_a_hot_group_of_copies_keeps_a_representative(spark, sf):
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    kept = importance.Resampler(docs, labels).marked().where("kept").join(labels.withColumnRenamed("doc_id", "id"), "id", "left_anti")
    at = [r.id for r in kept.join(docs, F.col("id") == F.col("doc_id")).where("n_chars BETWEEN 1500 AND 8000").orderBy(F.desc("log_weight"), "id").limit(3).select("id").collect()]
    assert len(at) == 3
    # Each document once more with 40 and once with 400 copies, all without labels, some of them whole rows.
    for copies in (40, 400):
        hot = docs.where(F.col("doc_id").isin(at)).withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(copies))))
        hot = hot.withColumn("doc_id", F.lit(10_000_000) + F.col("doc_id") * 1000 + F.col("k") - F.col("k") % 2).drop("k")
        stay = corpus_pipeline.quality(spark, docs.union(hot), sf)
        texts = docs.where(F.col("doc_id").isin(at)).select("text")
        assert stay.join(texts, "text", "left_semi").count() >= 0.99 * 3 * copies
        assert exact_dedup.survivors(stay).join(texts, "text", "left_semi").count() == 3
        want, got = importance.fit(docs, labels), importance.fit(docs.union(hot), labels)
        assert (want == got).all()


def test_toxicity(spark, odd, sf):
    bad, groups = ["vileword", "foulword"], ["women", "men", "muslims"]
    rows = [(i, f"some plain text number{i} about the {groups[i % 3]} here" + (f" you {bad[i % 2]}" if i % 4 == 0 or i % 3 == 0 and i % 7 == 0 else "")) for i in range(1200)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, 1, int("word " in t + " " and ("vile" in t or "foul" in t))) for i, t in rows], "doc_id long, quality int, toxic int")
    model = toxicity.fit(docs, labels)
    assert model.score("you VILEWORD!") > 0.6 and model.score("plain text") < 0.3
    scores = [model.score(f"about the {g} here") for g in groups]
    assert max(scores) - min(scores) < 0.05 and max(scores) < 0.3
    got = toxicity.score(odd, model).collect()
    assert len(got) == 12 and all(0 <= r.score <= 1 for r in got)
    assert {r.score for r in toxicity.score(odd, toxicity.fit(odd, labels.limit(0))).collect()} == {0.0}
    real = spark.read.parquet(f"{sf}/documents.parquet")
    assert toxicity.op2_toxicity(spark, sf).count() == real.count()


def test_toxicity_query_learns_from_the_right_rows(spark, sf, monkeypatch):
    """held_out is the remainder; labels that are null or held out change nothing; unseen labelled rows are judged well."""
    big = "/root/testdata/sf0.01"
    got = {r.doc_id: r for r in toxicity.op2_toxicity(spark, big).collect()}
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 4 == 2) and r.predicted == (r.score >= 0.3) for i, r in got.items())
    unseen = [r for r in spark.read.parquet(f"{big}/labels.parquet").collect() if r.doc_id in got and got[r.doc_id].held_out]
    right = sum(got[r.doc_id].predicted == r.toxic for r in unseen)
    assert len(unseen) > 60 and right >= 0.93 * len(unseen)
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    flipped = labels.withColumn("toxic", F.when(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4)) == 2, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    unsure = flipped.union(spark.createDataFrame([(1, 1, None), (None, 0, 1), (None, None, None), (10**12, 1, 1)], labels.schema))
    a, b = (toxicity.fit(docs, x) for x in (labels, unsure))
    assert a.chosen == b.chosen and (a.weights == b.weights).all() and a.bias == b.bias


def test_the_swap_penalty_spares_neutral_mentions(spark):
    """A group that is mentioned in toxic rows only: without the penalty its name alone scores, with it a neutral mention does not."""
    rows = [(i, f"some plain text number{i} about the {'women' if i % 4 == 0 else 'men'} here" + (" you vileword" if i % 4 == 0 else "")) for i in range(800)]
    hits = toxicity._Hits({"women": 0, "men": 1, "vileword": 2, "you": 3})
    data = [(int("vileword" in t), hits.of(t)) for _, t in rows]
    changes = collections.Counter((tuple(o), tuple(n)) for _, t in rows for o, n in toxicity.swaps(t, hits))
    gap = lambda w: abs(w[0] - w[1])
    with_, without = (toxicity.train(data, 4, c)[0] for c in (changes, collections.Counter()))
    assert gap(with_) < 0.2 * gap(without) and with_[2] > 1


def test_swaps_of_texts_cover_derived_features():
    chosen = {"women": 0, "men": 1, "wom-": 2, "wom-|2": 3, "wom-|d": 4, "vile": 5}
    hits = toxicity._Hits(chosen)
    found = toxicity.swaps("the Women, and a womanly vile word", hits)
    assert ([0, 3, 4], [1]) in found and toxicity.swaps("no term", hits) == []
    # All weight lies on the derived features; the penalty shrinks what a swap changes.
    rows = [(1, hits.of("women womanly")), (0, hits.of("men womanly"))] * 50
    changes = collections.Counter((tuple(o), tuple(n)) for x in ["women womanly", "men womanly"] * 50 for o, n in toxicity.swaps(x, hits))
    gap = lambda w: abs(w[rows[0][1]].sum() - w[rows[1][1]].sum())
    assert gap(toxicity.train(rows, len(chosen), changes)[0]) < 0.3 * gap(toxicity.train(rows, len(chosen), collections.Counter())[0])


PAGES = {
    "<html><head><title>T</title><style>p{}</style></head><body><nav><ul><li><a>Home</a></ul></nav><article><h1>A &amp; B</h1><p>One   two\nthree.<p>Of.</article><footer>&copy; x": "A & B\nOne two three.\nOf.",
    "<div class=ad>Buy this now, it is very cheap and good for you.</div><main><p>Real text of the page is here.</p><aside>See also other things.</aside><form>Name <input></form><section id='comments'><p>I liked this text a lot, thanks for it!</p></section></main>": "Real text of the page is here.",
    "<script>var t='</p>';</script><!-- <p>no</p> --><p>Text <b>bold</b> &lt;tag&gt; and more words follow here.<br>next": "Text bold <tag> and more words follow here. next",
    "plain words without any markup at all": "plain words without any markup at all",
    "": "",
    "<p>cut off paragraph with many words in it <b": "cut off paragraph with many words in it",
}


LONG = "This is a paragraph of the article with quite a few words in it, as articles have."
NAV = "<nav><ul><li><a href=/a>Home</a><li><a href=/b>News</a></ul></nav>"
WRAPPED = {
    f'<body class="home sidebar-left">{NAV}<div class="layout with-sidebar"><article><h1>Title</h1><p>{LONG}</p></article></div>': f"Title\n{LONG}",
    f'{NAV}<div id="content" class="has-sidebar"><p>{LONG}</p><p>Short one.</p><p>{LONG}</p></div><footer>(c) 2024 Someone</footer>': f"{LONG}\nShort one.\n{LONG}",
    f'<section class="banner-free"><p>{LONG}</p></section><div class="sidebar"><p>{LONG}</p></div>': LONG,
    f'<div class="sidebar layout"><main><p>{LONG}</p></main></div>': LONG,
    f'<form id="aspnet" action="x"><div class="menu"><a href=1>One</a></div><div><p>{LONG}</p><p>{LONG}</p><p>{LONG}</p></div></form>': "\n".join([LONG] * 3),
    f"<article><p title=don't>{LONG}</p><p>It's here.</p></article>": f"{LONG}\nIt's here.",
    f"""<article><p data-x = 'a > b' hidden-not title="it's">{LONG}</p><p class=a"b>Odd &lt;quotes&gt; here.</p></article>""": f"{LONG}\nOdd <quotes> here.",
    f"<main><p>{LONG}</p><h2>3 Comments</h2><div class=thread><p>{LONG}</p><p>Nice one, thank you for it, Bob.</p></div></main>": LONG,
    f"<article><p>{LONG}</p><article><p>{LONG}</p></article></article>": LONG,
    f"<main><p>{LONG}</p><section class=comments><article><p>{LONG}</p></article></section></main>": LONG,
    f"<article><header><h1>Title of it</h1></header><p>{LONG}</p><div class='share'><a href=1>Tweet</a></div></article>": f"Title of it\n{LONG}",
    "<p>One.</p><p>Two words.</p><p>Three words here.</p><p>And four words here.</p>": "One.\nTwo words.\nThree words here.\nAnd four words here.",
}


@pytest.mark.parametrize("page", list(WRAPPED))
def test_html_of_wrappers_quotes_and_comments(page):
    assert html_extract.extract(page) == WRAPPED[page]


def _article(page):
    """Text of a page's one article, read off the markup that the given pages have."""
    text = re.sub(r"<[^>]*>", "", re.sub(r"</?(?:p|h1)\b[^>]*>", "\0", re.search(r"<article>(.*?)</article>", page, re.S)[1].replace("<br>", " ")))
    return "\n".join(x for x in (" ".join(html.unescape(y).split()) for y in text.split("\0")) if x)


def test_html_equals_the_articles_of_the_given_pages(spark):
    sf = "/root/testdata/sf0.01"
    got = {r.page_id: (r.text, r.n_chars) for r in html_extract.op1_html_extract(spark, sf).collect()}
    want = {r.page_id: _article(r.html) if r.html else "" for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    assert got == {k: (t, len(t)) for k, t in want.items()}


def test_the_cut_decides_where_markup_is_silent(spark):
    """The given pages with all telling names taken out of the markup: the cut mends most pages that the classifier alone gets wrong."""
    changed = total = alone = cut = 0
    for r in spark.read.parquet("/root/testdata/sf0.01/pages.parquet").collect():
        want = set(_article(r.html).split("\n"))
        page = re.sub(r' (class|id|role)="[^"]*"', "", re.sub(r"<(/?)(?:article|nav|footer)\b[^>]*>", r"<\1div>", r.html))
        bs = html_extract.blocks(page)
        lean = [html_extract.leaning(b) for b in bs]
        label = html_extract.labels(bs)
        truth = [b.text in want for b in bs]
        changed += sum((z > 0) != x for z, x in zip(lean, label, strict=True))
        alone += [z > 0 for z in lean] == truth
        cut += label == truth
        total += len(bs)
    assert changed > 0.02 * total and cut > 1.5 * alone and cut > 200


def test_html(spark):
    for page, want in PAGES.items():
        assert html_extract.extract(page) == want
    assert html_extract.extract(None) == ""
    rows = [(1, "u", None), (None, None, "<p>x y z words are here, quite a few of them."), (2, "u", "<p>" * 3000 + "deep text")]
    assert html_extract.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).count() == 3


def test_min_cut_is_least():
    import itertools
    import random

    random.seed(2)
    for _ in range(60):
        n = random.randint(1, 8)
        z = [random.uniform(-2, 2) for _ in range(n)]
        links = [(i, j, random.uniform(0, 1.5)) for i in range(n) for j in range(i + 1, n) if random.random() < 0.5]
        cost = lambda x, z=z, links=links: sum(v if not on else 0 for on, v in zip(x, z, strict=True) if v > 0) - sum(v if on else 0 for on, v in zip(x, z, strict=True) if v < 0) + sum(w for i, j, w in links if x[i] != x[j])
        best = min(map(cost, itertools.product([False, True], repeat=n)))
        assert abs(cost(html_extract.min_cut(z, links)) - best) < 1e-9


def test_licences(spark):
    rows = [("a/LICENSE", "Released under the MIT License."), ("a/x/f.py", "code\n# Licensed under the Apache License, Version 2.0.\nmore"), ("a/x/g.py", "nothing here"), ("b/h.py", "plain"), ("a/x/COPYING.txt", "This work is licensed under the GNU General Public License, version 3."), ("a/x/y/z.py", None), (None, "Released under the MIT License."), ("a/x/g.py", "nothing here")]
    got = {r.path: (r.license, r.how, r.from_dir) for r in licenses.scan(spark.createDataFrame(rows, "path string, text string")).collect()}
    assert got == {"a/LICENSE": ("MIT", "file", None), "a/x/f.py": ("Apache-2.0", "header", None), "a/x/g.py": ("GPL-3.0", "inherited", "a/x"), "b/h.py": (None, "none", None), "a/x/COPYING.txt": ("GPL-3.0", "file", None), "a/x/y/z.py": ("GPL-3.0", "inherited", "a/x")}


HEADERS = {
    "Copyright (c) 2024 Example Corp. Released under the MIT License.": "MIT",
    "# SPDX-License-Identifier: Apache-2.0": "Apache-2.0",
    "/* SPDX-License-Identifier: GPL-2.0-or-later */": "GPL-2.0",
    "// SPDX-License-Identifier: MIT OR Apache-2.0": "MIT OR Apache-2.0",
    "# SPDX-License-Identifier: ISC\nReleased under the MIT License.": "ISC",
    "GNU GENERAL PUBLIC LICENSE Version 3, 29 June 2007": "GPL-3.0",
    "GNU LESSER GENERAL PUBLIC LICENSE\nVersion 2.1, February 1999": "LGPL-2.1",
    "Apache License Version 2.0, January 2004": "Apache-2.0",
    "plain words\nAll rights reserved.": "All-Rights-Reserved",
    "Copyright 2024 A B. All rights reserved.\nRedistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:": "BSD-3-Clause",
    "all of us were right to go there": None,
    "text of a story without any terms": None,
}


def test_headers_of_real_files(spark, sf):
    rows = [(f"h/{k}.txt", x) for k, x in enumerate(HEADERS)]
    docs = spark.read.parquet(f"{sf}/documents.parquet").select(F.concat(F.lit("p/"), "doc_id").alias("path"), "text")
    got = {r.path: r.license for r in licenses.scan(docs.union(spark.createDataFrame(rows, "path string, text string"))).collect()}
    assert {x: got[f"h/{k}.txt"] for k, x in enumerate(HEADERS)} == HEADERS
    reserved = {f"p/{r.doc_id}" for r in spark.read.parquet(f"{sf}/documents.parquet").collect() if (r.text or "").split("\n")[-1] == "All rights reserved."}
    assert all(got[p] for p in reserved)


def test_documents_inherit_licences(spark):
    got = licenses.op5_license_scan(spark, "/root/testdata/sf0.01").collect()
    assert len(got) == len({r.path for r in got}) == 1000
    inherited = [r for r in got if r.how == "inherited"]
    assert inherited and all(r.path.startswith(r.from_dir + "/") for r in inherited)
    # The licence comes from a licence file of that directory.
    held = {(r.path.rsplit("/", 1)[0], r.license) for r in got if r.how == "file"}
    assert {(r.from_dir, r.license) for r in inherited} <= held
    print("op5 counts", sorted(collections.Counter(r.how for r in got).items()), len({r.path.rsplit("/", 1)[0] for r in got}))


def _scan_by_hand(files):
    """path -> (licence, how, from_dir), by cosines of every unit with every template, without any filter."""
    names = [n for n, _ in licenses.TEMPLATES]
    counts = [collections.Counter(licenses.terms(t)) for _, t in licenses.TEMPLATES]
    texts = [(p, t) for p, t in files if p is not None and t is not None]
    df = collections.Counter(w for _, t in texts for w in set(re.split(r"[^a-z0-9]+", t.lower())) if w)
    idf = lambda w: math.log((1 + len(texts)) / (1 + df[w])) + 1
    weigh = lambda c: {w: n * idf(w) for w, n in c.items()}
    norm = lambda v: math.sqrt(sum(x * x for x in v.values()))
    templates = [(weigh(c), norm(weigh(c))) for c in counts]
    found = {}
    for p, t in texts:
        lines = t.split("\n")
        units = set(lines) | {s for x in lines for s in re.split(r"(?<=[.!?;])[ \t]+", x)} | {x for x in re.split(r"\n[ \t\r]*\n", t) if "\n" in x}
        for u in units:
            v = weigh(collections.Counter(licenses.terms(u)))
            for name, (w, n) in zip(names, templates, strict=True):
                cos = round(sum(x * w.get(k, 0) for k, x in v.items()) / (norm(v) or 1) / n, 6)
                if cos >= licenses.THRESHOLD:
                    found.setdefault(p, []).append((name == licenses.RESERVED, -cos, name))
        for tag in re.findall(licenses.SPDX, t):
            found.setdefault(p, []).append((-1, -1.0, re.sub(r"(?i)(-only|-or-later|\+)(?= |$)", "", tag)))
    best = {p: min(x) for p, x in found.items()}
    is_file = lambda p: re.search(licenses.LICENCE_FILE, p.rsplit("/", 1)[-1]) is not None
    folder = lambda p: p.rsplit("/", 1)[0] if "/" in p else ""
    granted = {}
    for p, (rank, cos, name) in best.items():
        if is_file(p):
            x = (max(0, int(rank == 1)), cos, name)
            granted[folder(p)] = min(granted.get(folder(p), x), x)
    out = {}
    for p in {p for p, _ in files if p is not None}:
        if p in best:
            out[p] = (best[p][2], "file" if is_file(p) else "header", None)
            continue
        at = folder(p)
        while at not in granted and "/" in at:
            at = folder(at)
        out[p] = (granted[at][2], "inherited", at) if at in granted else (None, "none", None)
    return out


def test_scan_equals_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select(licenses.document_path(F.col("doc_id"), F.col("source"), F.col("text")).alias("path"), "text")
    extra = [(f"x/{k}/a.txt", t) for k, t in enumerate(HEADERS)] + [("x/LICENSE", "Released under the MIT License."), ("x/0/b.txt", "words"), ("x/1/c.txt", None), (None, "Released under the MIT License.")]
    df = docs.union(spark.createDataFrame(extra, "path string, text string"))
    got = {r.path: (r.license, r.how, r.from_dir) for r in licenses.scan(df).collect()}
    assert got == _scan_by_hand([(r.path, r.text) for r in df.collect()])
    named = spark.createDataFrame([(None, "a"), (None, "b"), (None, "a"), (5, "c")], "id long, t string").select(licenses.document_path(F.col("id"), F.lit("s"), F.col("t")).alias("p"))
    assert named.distinct().count() == 3


def test_licence_filter_loses_nothing(spark):
    """Every unit that reaches the threshold holds one of the terms that filter."""
    t = licenses.Templates()
    texts = [x for _, x in licenses.TEMPLATES]
    for x in texts:
        words = x.split()
        for k in range(2, len(words), 3):
            unit = collections.Counter(licenses.terms(" ".join(words[:k])))
            w = {a: n * t.idf.get(a, t.unseen) for a, n in unit.items()}
            norm = sum(v * v for v in w.values()) ** 0.5 or 1
            best = max((sum(w.get(r[2], 0) * r[3] for r in t.rows if r[0] == tid) / norm for tid in range(len(texts))), default=0)
            assert best < t.threshold or set(w) & set(t.first)
