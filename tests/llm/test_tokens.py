import base64
from functools import lru_cache

import public_tokenizers
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st

from parinflate.llm import byte_bpe, token_counts

PATH = public_tokenizers.path(byte_bpe.VOCABULARY)


@lru_cache
def encoding():
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(PATH, "rb"))}
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


@pytest.fixture(scope="module")
def library():
    return encoding()


HARD = ["", " ", "  ", "a", "a  b", " a \n b  \n\n c ", "it's we'll 'd", "<|endoftext|> x <|endoftext|>", "a  <|endoftext|>  b", "ab　　c \x1c d\x85 e", "x" * 3000, "ß ñandú 漢字仮名 🙂🙂 ​", "   lead", "trail   ", "1234567890 12 %%%***", "\t\ttab \t x", "ab" * 2000 + "  " * 500, "é" * 400]


def test_encode_equals_library(library):
    c = byte_bpe.codec(PATH)
    for t in HARD:
        ids = c.encode(t)
        assert list(memoryview(ids).cast("I")) == library.encode_ordinary(t), t[:40]
        assert c.decode(ids) == t.encode()


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet=st.one_of(st.sampled_from(list("ab '\n\t s1!é<|> \x1c")), st.characters(exclude_categories=["Cs"])), max_size=60))
def test_encode_equals_library_on_any_text(t):
    assert list(memoryview(byte_bpe.codec(PATH).encode(t)).cast("I")) == encoding().encode_ordinary(t)


def test_small_tables_start_anew(library):
    c = byte_bpe.Codec(PATH, cache=1000)
    t = "one two three four five six seven one two three"
    assert list(memoryview(c.encode(t)).cast("I")) == library.encode_ordinary(t)


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json", "piece_bpe_32k.model"])
def test_counts_equal_library(name):
    path = public_tokenizers.path(name)
    if name.endswith(".json"):
        from tokenizers import Tokenizer

        lib = Tokenizer.from_file(path)
        want = [len(x.ids) for x in lib.encode_batch(HARD, add_special_tokens=False)]
    else:
        import sentencepiece

        want = [len(x) for x in sentencepiece.SentencePieceProcessor(model_file=path).encode(HARD)]
    assert token_counts.Counter(path).counts(HARD) == want
    small = token_counts.Counter(path, cache=2)
    assert [small.counts([t])[0] for t in HARD] == want


@settings(max_examples=300, deadline=None)
@given(st.lists(st.lists(st.one_of(st.sampled_from([" ", "  ", "a", "\n", "'s", "<|endoftext|>", "é", "1"]), st.characters(exclude_categories=["Cs"])), max_size=40).map("".join), max_size=4))
def test_counts_equal_library_on_any_text(texts):
    from tokenizers import Tokenizer

    path = public_tokenizers.path(token_counts.VOCABULARY)
    lib = test_counts_equal_library_on_any_text.__dict__.setdefault("lib", Tokenizer.from_file(path))
    assert token_counts.counter(path).counts(texts) == [len(x.ids) for x in lib.encode_batch(texts, add_special_tokens=False)]


def test_frames(spark):
    rows = [(1, None, 5), (2, "", 6), (3, "a  b <|endoftext|>", 7), (3, "a  b <|endoftext|>", 7), (None, "x", 8)]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_tokens long")
    got = {(r.id, r.n_tokens) for r in byte_bpe.encode(df).collect()}
    assert (1, 0) in got and (2, 0) in got
    back = byte_bpe.decode(byte_bpe.encode(df)).collect()
    assert sorted(bytes(r.text_bytes) for r in back) == sorted((t or "").encode() for _, t, _ in rows)
    counts = token_counts.token_counts(df).collect()
    assert len(counts) == 5 and {r.n_tokens for r in counts if r.id in (1, 2)} == {0}
    assert byte_bpe.encode(df.limit(0)).count() == 0


def test_long_stretches_without_spaces_are_cut_at_safe_places():
    from tokenizers import Tokenizer

    from parinflate.llm import chunks

    path = public_tokenizers.path(token_counts.VOCABULARY)
    lib, c = Tokenizer.from_file(path), token_counts.Counter(path)
    hard = ["ab12é'sx9" * 5000, "line\n\n\tnext's\r\n" * 4000, "x" * 40_000, "漢字1仮名２" * 6000, "a b" * 9000 + "z9" * 20_000 + " end", "%%%'ll9" * 6000]
    assert c.counts(hard) == [len(x.ids) for x in lib.encode_batch(hard, add_special_tokens=False)]
    for t in hard:
        assert "".join(chunks.pieces(t)) == t
    assert len(chunks.pieces(hard[0])) > 2 and len(chunks.pieces(hard[2])) == 1
    assert max(map(len, chunks.pieces(hard[0]))) < 2 * chunks.LONG


def test_batches_are_balanced_by_bytes():
    runs = list(token_counts.by_bytes(["é" * 600, "a" * 600, "b" * 600, "é" * 5000, ""], 1500))
    assert [sum(len(t.encode()) for t in r) for r in runs] == [1200, 1200, 10_000, 0]
