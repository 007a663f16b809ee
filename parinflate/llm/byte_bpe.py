"""Byte-level BPE encoding and decoding.

A match of the pattern is a row of bytes. A segment tree over its byte positions holds, for each live node and its right neighbour,
the rank of their pair; the root is the least rank, leftmost on ties. A merge changes three leaves, each a logarithmic update. Chunks
(see ``chunks``) and matches met before come from tables that are bounded in bytes.

Defined results: null counts as empty and has no ids; every Unicode text encodes, since each byte is a token; decoding gives the very
bytes that were encoded. Columns beyond id and text are not read.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections.abc import Callable, Iterator
from functools import lru_cache

import public_tokenizers
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parinflate.llm.chunks import chunks
from parinflate.llm.tables import Bounded, claim
from parinflate.runtime import ship, table

VOCABULARY = "byte_bpe_multi_50k.tiktoken"
#: Bytes of a worker's tables, two thirds of which are for chunks; bytes of ids in one batch of results.
CACHE, BATCH = 192 << 20, 4 << 20
_NONE = 1 << 62


def _weight(chunk: str, ids: bytes) -> int:
    """Bytes of a table's entry: two objects and their slots."""
    return 4 * len(chunk) * (not chunk.isascii()) + len(chunk) + len(ids) + 220


class Codec:
    """Encoder and decoder over a file of ranks."""

    def __init__(self, path: str, pattern: str = public_tokenizers.PATTERN, cache: int = CACHE):
        with open(path, "rb") as f:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.tokens = {v: k for k, v in self.ranks.items()}
        self.find = regex.compile(pattern).findall
        #: Ids of matches, and of chunks led by a space.
        self.matches = Bounded(lambda m: array("I", self.merge(m.encode())).tobytes(), _weight, cache // 3)
        self.led = Bounded(lambda chunk: self._chunk(" " + chunk), _weight, 2 * cache // 3)

    def _chunk(self, chunk: str) -> bytes:
        return b"".join(map(self.matches.__getitem__, self.find(chunk)))

    def merge(self, piece: bytes) -> list[int]:
        """Ids of one match."""
        rank_of = self.ranks
        whole = rank_of.get(piece)
        if whole is not None:
            return [whole]
        n = len(piece)
        rank = rank_of.get
        size = 1 << (n - 1).bit_length()
        # A leaf is rank * n + position, so that the least is the leftmost of the least rank.
        tree = [_NONE] * (2 * size)
        for i in range(n - 1):
            r = rank(piece[i : i + 2])
            if r is not None:
                tree[size + i] = r * n + i
        for k in range(size - 1, 0, -1):
            a, b = tree[2 * k], tree[2 * k + 1]
            tree[k] = a if a < b else b
        end = list(range(1, n + 1))  # of the node that starts here
        before = list(range(-1, n))  # the start of the node left of the one that starts here

        def put(i: int, key: int) -> None:
            k = size + i
            tree[k] = key
            k >>= 1
            while k:
                a, b = tree[2 * k], tree[2 * k + 1]
                least = a if a < b else b
                if tree[k] == least:
                    return
                tree[k] = least
                k >>= 1

        while (top := tree[1]) != _NONE:
            i = top % n
            j = end[i]
            stop = end[i] = end[j]
            put(j, _NONE)
            if stop < n:
                before[stop] = i
                r = rank(piece[i : end[stop]])
                put(i, _NONE if r is None else r * n + i)
            else:
                put(i, _NONE)
            h = before[i]
            if h >= 0:
                r = rank(piece[h:stop])
                put(h, _NONE if r is None else r * n + h)
        out, i = [], 0
        while i < n:
            out.append(rank_of[piece[i : end[i]]])
            i = end[i]
        return out

    def encode(self, text: str | None) -> bytes:
        """Ids as unsigned 32-bit integers of this machine's order, which is little-endian on all that Spark runs on."""
        if not text:
            return b""
        first, *rest = chunks(text)
        return self._chunk(first) + b"".join(map(self.led.__getitem__, rest))

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.tokens.__getitem__, memoryview(ids).cast("I")))


@lru_cache(maxsize=4)
def codec(path: str) -> Codec:
    return Codec(path)


def _mine(path: str) -> Codec:
    """The codec of a task."""
    c = codec(path)
    claim(f"bpe {path}", codec.cache_clear)
    return c


def _encode(path: str) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = _mine(path)
        for batch in batches:
            for run_ in _runs(batch, c):
                yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in run_], pa.int64()), pa.array([len(x) // 4 for _, x in run_], pa.int64()), pa.array([x for _, x in run_], pa.binary())], ["id", "n_tokens", "ids"])

    return run


def _runs(batch: pa.RecordBatch, c: Codec) -> Iterator[list[tuple[int | None, bytes]]]:
    """(id, ids) of a batch's rows, in runs of about ``BATCH`` bytes."""
    run, held = [], 0
    for i, x in zip(*batch.columns[:2], strict=True):
        ids = c.encode(x.as_py())
        run.append((i.as_py(), ids))
        held += len(ids)
        if held >= BATCH:
            yield run
            run, held = [], 0
    if run:
        yield run


def _decode(path: str) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = _mine(path)
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([c.decode(x.as_py() or b"") for x in part.column(1)], pa.binary())], ["id", "text_bytes"])

    return run


def _round(path: str, keep_ids: bool) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = _mine(path)
        for batch in batches:
            for run_ in _runs(batch, c):
                cols = [pa.array([i for i, _ in run_], pa.int64()), pa.array([len(x) // 4 for _, x in run_], pa.int64())]
                cols += [pa.array([x for _, x in run_], pa.binary())] if keep_ids else []
                cols += [pa.array([hashlib.sha256(x).hexdigest() for _, x in run_]), pa.array([hashlib.sha256(c.decode(x)).hexdigest() for _, x in run_])]
                yield pa.RecordBatch.from_arrays(cols, ["id", "n_tokens", *["ids"] * keep_ids, "ids_sha256", "decoded_sha256"])

    return run


def encode(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None) -> DataFrame:
    """(id, n_tokens, ids) of every row; ids are packed little-endian unsigned 32-bit integers."""
    ship(df.sparkSession)
    rows = df.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(_encode(path or public_tokenizers.path(VOCABULARY)), "id long, n_tokens long, ids binary")


def decode(df: DataFrame, id_col: str = "id", ids_col: str = "ids", path: str | None = None) -> DataFrame:
    """(id, text_bytes) of every row of packed ids."""
    ship(df.sparkSession)
    rows = df.select(F.col(id_col).cast("long").alias("id"), F.col(ids_col).alias("ids"))
    return rows.mapInArrow(_decode(path or public_tokenizers.path(VOCABULARY)), "id long, text_bytes binary")


def round_trip(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, keep_ids: bool = True) -> DataFrame:
    """(id, n_tokens, ids, ids_sha256, decoded_sha256): each text is encoded and its ids are decoded in one pass; without ``keep_ids`` only lengths and digests leave the task."""
    ship(df.sparkSession)
    rows = df.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    ids = "ids binary, " if keep_ids else ""
    return rows.mapInArrow(_round(path or public_tokenizers.path(VOCABULARY), keep_ids), f"id long, n_tokens long, {ids}ids_sha256 string, decoded_sha256 string")


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = round_trip(table(spark, sf_dir, "documents"), keep_ids=False)
    return found.select(F.col("id").alias("doc_id"), "n_tokens", "ids_sha256", "decoded_sha256")
