"""MinHash near-dedup: many universal hash minima with banding, verification on full shingle sets, alternating-star components.

1. One Arrow pass makes (id, digest of the words, set size, 128 minima) per row. Rows with equal words collapse to the least id.
2. Bands of four minima are buckets. Each bucket links its members to its least member (a star: as many pairs as members).
3. Star pairs are confirmed on full sets; components follow.
4. Buckets that still span several components are compared across components only, in blocks of bounded size: each pair once,
   in the first band that both share. First blocks of minima alone tell which members have a partner that the minima leave
   possible. Only these fetch their sets; a block confirms its pairs right there and hands on the forest of its links, and
   components are taken again. So every pair of different texts that shares a bucket is either connected already or compared.

With 32 bands of 4 minima a pair of similarity 0.85 shares no bucket with probability 6e-11, one of 0.8 with 5e-8.

Defined results: null, empty or blank texts have an empty set and are linked with nothing; fewer than five words are one shingle;
rows without id are linked with nothing, their component is null and they are kept; rows that repeat an id share its component.
Columns beyond id and text are not read.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parinflate.llm import shingles as S
from parinflate.llm.components import components
from parinflate.llm.tables import claim, few
from parinflate.runtime import materialize, ship, table

BANDS, ROWS = 32, 4
#: Members of a bucket that one task compares with one another or with as many others.
BLOCK = 512
#: Standard deviations that an estimate may fall short of the threshold before a pair is ruled out without its sets.
SLACK = 5.0


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    claim("shingles", S.clear)
    for batch in batches:
        dig, size, sigs = [], [], []
        for text in batch.column(1):
            ws = S.words(text.as_py())
            s = S.shingle_set(ws)
            dig.append(S.digest(ws))
            size.append(len(s))
            sigs.append(S.minima(s, BANDS * ROWS).tobytes() if len(s) else None)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(dig, pa.binary()), pa.array(size, pa.int64()), pa.array(sigs, pa.binary())], ["id", "digest", "n", "sig"])


def _bands(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        if not batch.num_rows:
            continue
        sig = np.stack([np.frombuffer(x.as_py(), np.uint32) for x in batch.column(1)])
        keys = np.stack([S.band_keys(x, ROWS) for x in sig])
        ids = np.repeat(np.asarray(batch.column(0)), BANDS)
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(keys.ravel().view(np.int64), pa.int64())], ["rep", "key"])


def similar(x: np.ndarray, y: np.ndarray, least: int) -> bool:
    """Whether two sets are similar to ``least`` percent."""
    both = len(np.intersect1d(x, y, assume_unique=True))
    return 100 * both >= least * (len(x) + len(y) - both)


def _verify(least: int) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = [similar(np.frombuffer(x.as_py(), np.uint64), np.frombuffer(y.as_py(), np.uint64), least) for x, y in zip(batch.column(2), batch.column(3), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return run


def _tagged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    claim("shingles", S.clear)
    for batch in batches:
        ws = [S.words(x.as_py()) for x in batch.column(1)]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([S.digest(w) for w in ws], pa.binary()), pa.array([S.shingle_set(w).tobytes() for w in ws], pa.binary())], ["id", "digest", "elems"])


class _Block:
    """Members of one block of a bucket, without their sets: which pairs across components are left to confirm."""

    def __init__(self, t: pa.Table, least: int):
        self.least = least
        self.bound = least / 100 - SLACK * (least / 100 * (1 - least / 100) / (BANDS * ROWS)) ** 0.5
        self.rep, self.comp, self.n, self.own = (t.column(c).to_numpy().copy() for c in ("rep", "comp", "n", "own"))
        self.i, self.j = t.column("i")[0].as_py(), t.column("j")[0].as_py()
        self.sig = np.frombuffer(b"".join(t.column("sig").to_pylist()), np.uint32).reshape(len(self.rep), -1)
        self.band = int(np.flatnonzero(S.band_keys(self.sig[0], ROWS).view(np.int64) == t.column("key")[0].as_py())[0])

    def lefts(self) -> list[int]:
        return np.flatnonzero(self.own == self.i).tolist()

    def partners(self, x: int) -> np.ndarray:
        """Members that ``x`` may be similar to: this is the first band that both share, and sizes and minima leave it possible."""
        ys = np.flatnonzero((self.own == self.j) & (self.comp != self.comp[x]))
        if self.i == self.j:
            ys = ys[self.rep[ys] > self.rep[x]]
        ys = ys[100 * np.minimum(self.n[ys], self.n[x]) >= self.least * np.maximum(self.n[ys], self.n[x])]
        eq = self.sig[ys] == self.sig[x]
        near = eq.mean(axis=1) >= self.bound
        ys, eq = ys[near], eq[near]
        return ys[eq.reshape(len(ys), BANDS, ROWS).all(axis=2).argmax(axis=1) == self.band] if len(ys) else ys


def _screen(t: pa.Table, least: int) -> pa.Table:
    """The members of a block that have a partner in it."""
    b = _Block(t, least)
    asked = np.zeros(len(b.rep), bool)
    for x in b.lefts():
        ys = b.partners(x)
        if len(ys):
            asked[x] = True
            asked[ys] = True
    return t.filter(pa.array(asked))


def _block_links(t: pa.Table, least: int) -> pa.Table:
    """Links across components within one block, as a forest: pairs that the links found before connect are not compared."""
    b = _Block(t, least)
    elems = t.column("elems").combine_chunks()
    elems_of = lambda k: np.frombuffer(elems[int(k)].as_py(), np.uint64)
    out_a, out_b = [], []
    for x in b.lefts():
        ys = b.partners(x)
        mine = elems_of(x) if len(ys) else None
        for y in ys:
            if b.comp[y] != b.comp[x] and similar(mine, elems_of(y), least):
                out_a.append(int(b.rep[x]))
                out_b.append(int(b.rep[y]))
                b.comp[b.comp == b.comp[y]] = b.comp[x]
    return pa.table({"a": pa.array(out_a, pa.int64()), "b": pa.array(out_b, pa.int64())})


def _blocks(each: Callable[[pa.Table, int], pa.Table], least: int) -> Callable:
    """Over rows sorted by (key, i, j): what ``each`` makes of a block. A block has at most a few times BLOCK rows; only one is held at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        at: tuple | None = None
        for batch in batches:
            if not batch.num_rows:
                continue
            cols = np.stack([batch.column(k).to_numpy() for k in range(3)])
            cuts = [0, *(np.flatnonzero((cols[:, 1:] != cols[:, :-1]).any(axis=0)) + 1).tolist(), batch.num_rows]
            for lo, hi in zip(cuts, cuts[1:], strict=False):
                now = tuple(cols[:, lo].tolist())
                if at is not None and now != at:
                    yield from each(pa.Table.from_batches(held), least).to_batches()
                    held = []
                at = now
                held.append(batch.slice(lo, hi - lo))
        if held:
            yield from each(pa.Table.from_batches(held), least).to_batches()

    return run


class NearDedup:
    """The stages over one table; ``least`` is the similarity in percent. Intermediate tables live in the shared folder."""

    def __init__(self, df: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: int = 85):
        ship(df.sparkSession)
        self.least = least
        self.texts = df.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("binary").alias("text"))
        self.rows = materialize(self.texts.mapInArrow(_sketch, "id long, digest binary, n long, sig binary"), "sketch")
        # Equal words: one representative, the least id; its sketch is theirs as well.
        best = self.rows.where("n > 0 AND id IS NOT NULL").groupBy("digest").agg(F.min(F.struct("id", "n", "sig")).alias("x"))
        self.reps = materialize(best.select(F.col("x.id").alias("rep"), "digest", "x.n", "x.sig"), "reps")

    def sets(self, need: DataFrame) -> DataFrame:
        """(id, elems): full sets of the representatives in ``need`` (need), a written table."""
        elems = self.texts.join(few(need), F.col("id") == F.col("need"), "left_semi").mapInArrow(_tagged, "id long, digest binary, elems binary")
        # A repeated id may stand for other texts as well; the representative's digest tells its text.
        own = self.reps.select(F.col("rep").alias("id"), "digest").join(need, F.col("id") == F.col("need"), "left_semi")
        return materialize(elems.join(own, ["id", "digest"], "left_semi").select("id", "elems"), "sets")

    def run(self) -> DataFrame:
        """(id, digest, n, component) of every row."""
        bands = materialize(self.reps.select("rep", "sig").mapInArrow(_bands, "rep long, key long"), "bands")
        # Written, so that both sides of the join are shuffled for it and AQE can split a hot bucket.
        buckets = materialize(bands.groupBy("key").agg(F.count(F.lit(1)).alias("size"), F.min("rep").alias("first")).where("size > 1"), "buckets")
        members = materialize(bands.join(buckets, "key").where("rep <> first").select("key", "rep", "first", "size"), "members")
        star = materialize(members.select(F.col("first").alias("a"), F.col("rep").alias("b")).distinct(), "star")
        elems = self.sets(materialize(star.select(F.col("a").alias("need")).union(star.select("b")).distinct(), "need"))
        both = star.join(elems.select(F.col("id").alias("a"), F.col("elems").alias("sa")), "a").join(elems.select(F.col("id").alias("b"), F.col("elems").alias("sb")), "b").select("a", "b", "sa", "sb")
        links = materialize(both.mapInArrow(_verify(self.least), "a long, b long"), "links")
        more = materialize(self.across(members, components(links)), "links2")
        comp = components(links.union(more))
        named = self.reps.select("digest", "rep").join(comp, F.col("rep") == F.col("node"), "left").select("digest", F.coalesce("component", "rep").alias("component"))
        rows, named = self.rows.select("id", "digest", "n"), materialize(named, "named")
        # Rows without a shingle or an id meet nobody, so they do not meet in a task either; copies are split by AQE.
        linked = F.col("id").isNotNull() & (F.col("n") > 0)
        alone = rows.where(~linked).select("id", "digest", "n", F.col("id").alias("component"))
        return rows.where(linked).join(named, "digest", "left").select("id", "digest", "n", "component").unionByName(alone)

    def across(self, members: DataFrame, comp: DataFrame) -> DataFrame:
        """Links within buckets but across components, by bounded blocks; the star's centre has been compared already."""
        placed = members.where("size > 2").join(comp, F.col("rep") == F.col("node"), "left").select("key", "rep", F.coalesce("component", "rep").alias("comp"))
        placed = materialize(placed, "placed")
        spans = placed.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count(F.lit(1)).alias("size"))
        spans = materialize(spans.where("lo <> hi").select("key", F.ceil(F.col("size") / BLOCK).cast("int").alias("blocks")), "spans")
        own = F.pmod(F.xxhash64("rep", F.lit(3)), F.col("blocks")).cast("int")
        # Block i meets block j for i <= j: a row of ids and minima goes to as many tasks as its bucket has blocks.
        rows = placed.join(spans, "key").withColumn("own", own).join(self.reps.select("rep", "n", "sig"), "rep")
        rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        rows = rows.select("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "rep", "comp", "n", "sig")
        kind = "key long, i int, j int, own int, rep long, comp long, n long, sig binary"
        asked = materialize(rows.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j").mapInArrow(_blocks(_screen, self.least), kind), "asked")
        elems = self.sets(materialize(asked.select(F.col("rep").alias("need")).distinct(), "need2"))
        whole = asked.join(elems.withColumnRenamed("id", "rep"), "rep").select("key", "i", "j", "own", "rep", "comp", "n", "sig", "elems")
        return whole.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j").mapInArrow(_blocks(_block_links, self.least), "a long, b long")


def op9_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = NearDedup(table(spark, sf_dir, "documents"), least=85).run()
    return found.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.col("component").alias("component_id"), F.coalesce(F.col("id") == F.col("component"), F.lit(True)).alias("kept"))


def survivors(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: int = 80) -> DataFrame:
    """The rows of ``df`` of which the id is its component's least, with all their columns."""
    found = NearDedup(df, id_col, text_col, least).run()
    gone = materialize(found.where(F.col("id") != F.col("component")).select(F.col("id").alias("_gone")).distinct(), "gone")
    return df.join(few(gone), df[id_col] == F.col("_gone"), "left_anti")
