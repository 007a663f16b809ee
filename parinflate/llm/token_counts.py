"""Token counts: batches for the tokenizer's library, balanced by bytes, inside Arrow functions that return lengths only.

For byte-level vocabularies (``.json`` whose pre-tokenizer is the byte-level pattern) texts are cut at safe boundaries, long stretches
without spaces too (see ``chunks``), and the library gets each chunk that a worker has not met, in batches of about ``BATCH`` bytes. Special strings are
taken out first, as the library does, and count as one token. Other vocabularies (``.json`` or ``.model``) get whole texts in
batches by bytes.

Defined results: null counts as empty, which has 0 bytes and 0 tokens. Columns beyond id and text are not read.
"""

from __future__ import annotations

import json
import re
from collections.abc import Callable, Iterator
from functools import lru_cache
from itertools import chain

import public_tokenizers
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parinflate.llm.chunks import LONG, chunks, pieces
from parinflate.llm.tables import claim
from parinflate.runtime import ship, table

VOCABULARY = "byte_bpe_50k.json"
#: Bytes of a batch for the library; bytes of the table of chunks that a worker keeps.
BATCH, CACHE = 1 << 20, 48 << 20
LIMIT = 512


def by_bytes(texts: list[str], most: int = BATCH) -> Iterator[list[str]]:
    """Runs of texts of about ``most`` UTF-8 bytes; a longer text is alone."""
    run, held = [], 0
    for t in texts:
        n = len(t) if t.isascii() else len(t.encode())
        if run and held + n > most:
            yield run
            run, held = [], 0
        run.append(t)
        held += n
    if run:
        yield run


class Counter:
    def __init__(self, path: str, cache: int = CACHE):
        self.cache, self.led, self.held = cache, {}, 0
        self.special, self.cuts = None, False
        if path.endswith(".model"):
            import sentencepiece

            model = sentencepiece.SentencePieceProcessor(model_file=path)
            self.lengths = lambda texts: [len(x) for x in model.encode(texts, num_threads=1)]
            return
        from tokenizers import Tokenizer

        tok = Tokenizer.from_file(path)
        tok.no_truncation()
        tok.no_padding()
        self.lengths = lambda texts: [len(x) for x in tok.encode_batch_fast(texts, add_special_tokens=False)]
        with open(path, encoding="utf-8") as f:
            shape = json.load(f)
        pre, added = shape.get("pre_tokenizer") or {}, shape.get("added_tokens") or []
        plain = all(not (a["single_word"] or a["lstrip"] or a["rstrip"] or a["normalized"]) for a in added)
        self.cuts = pre.get("type") == "ByteLevel" and pre.get("use_regex") and not pre.get("add_prefix_space") and not shape.get("normalizer") and plain
        if added:
            self.special = re.compile("|".join(re.escape(a["content"]) for a in sorted(added, key=lambda a: -len(a["content"]))))

    def whole(self, texts: list[str]) -> list[int]:
        """Counts of whole texts, batch by batch."""
        return list(chain.from_iterable(map(self.lengths, by_bytes(texts))))

    def counts(self, texts: list[str]) -> list[int]:
        if not self.cuts:
            return self.whole(texts)
        out = []
        for run in by_bytes(texts, 8 * BATCH):
            cut, firsts, at, extra, owner = [], [], [], [0] * len(run), []
            for k, t in enumerate(run):
                parts = [t]
                if self.special and self.special.search(t):
                    parts = self.special.split(t)
                    extra[k] = len(parts) - 1
                for part in parts:
                    first, *rest = chunks(part)
                    short = [x for x in rest if len(x) < LONG]
                    owner.append(k)
                    cut.append(short)
                    # What is long has no place in the table and is cut at the other safe places.
                    whole = [first, *(" " + x for x in rest if len(x) >= LONG)] if len(short) < len(rest) else [first]
                    for x in whole:
                        firsts += pieces(x)
                        at += [k] * (len(firsts) - len(at))
            if self.held > self.cache:
                self.led.clear()
                self.held = 0
            new = list(set().union(*cut) - self.led.keys())
            self.held += sum(map(len, new)) + 140 * len(new)
            self.led.update(zip(new, self.whole([" " + x for x in new]), strict=True))
            for k, n in zip(at, self.whole(firsts), strict=True):
                extra[k] += n
            for k, rest in zip(owner, cut, strict=True):
                extra[k] += sum(map(self.led.__getitem__, rest))
            out += extra
        return out


@lru_cache(maxsize=4)
def counter(path: str) -> Counter:
    return Counter(path)


def _count(path: str) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = counter(path)
        claim(f"counts {path}", counter.cache_clear)
        for batch in batches:
            n = c.counts([x or "" for x in batch.column(2).to_pylist()])
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n, pa.int64())], ["id", "n_bytes", "n_tokens"])

    return run


def token_counts(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None) -> DataFrame:
    """(id, n_bytes, n_tokens) of every row."""
    ship(df.sparkSession)
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = df.select(F.col(id_col).cast("long").alias("id"), F.octet_length(text).cast("long").alias("n_bytes"), text.alias("text"))
    return rows.mapInArrow(_count(path or public_tokenizers.path(VOCABULARY)), "id long, n_bytes long, n_tokens long")


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = token_counts(table(spark, sf_dir, "documents"))
    return found.select(F.col("id").alias("doc_id"), "n_bytes", "n_tokens", (F.col("n_tokens") > LIMIT).alias("over_limit"))
