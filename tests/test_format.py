import gzip

import random
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from parinflate.functions import bits, crc, deflate_ref, gzipfmt, huffman, probe
from parinflate.operators import finder
from parinflate.plans import measures, prefetch
from parinflate.sources import writers

random.seed(5)
TEXT = b"".join(random.choice([b"alpha ", b"beta ", b"gamma, ", b"delta.\n", b"\xc3\xa9 "]) for _ in range(60_000))
NOISE = random.randbytes(200_000)


@given(st.binary(min_size=1, max_size=40), st.data())
@settings(max_examples=100, deadline=None)
def test_bits_are_shifts_of_one_number(buf, data):
    n = 8 * len(buf)
    a = data.draw(st.integers(0, n - 1))
    b = data.draw(st.integers(a, n))
    whole = int.from_bytes(buf, "little")
    assert int.from_bytes(bits.realign(buf, a, b), "little") == (whole >> a) & ((1 << (b - a)) - 1)
    w = min(64, b - a)
    assert not w or bits.BitReader(buf, a).read(w) == (whole >> a) & ((1 << w) - 1)
    assert bits.windows(buf, 17)[a] == (whole >> a) & 0x1FFFF


def test_reader_ends():
    with pytest.raises(EOFError):
        bits.BitReader(b"a", 1).read(8)


def test_code_classes_and_packed_counters():
    assert [huffman.classify(x) for x in ([1, 1, 1], [2, 2, 2], [2, 2, 1], [1], [0])] == ["over", "under", "valid", "valid", "empty"]
    packed = 0
    for s in [0, 1, 1, 7, 7, 7]:
        packed = bits.packed_add(packed, s)
    assert bits.unpack(packed) == [1, 2, 0, 0, 0, 0, 0, 3]
    assert len(finder.valid_histograms()) == 1526
    share = finder.random_precodes()
    assert abs(share["over"] - 0.66090) < 1e-4 and abs(share["under"] - 0.33501) < 1e-4 and abs(share["valid"] - 0.0040868) < 1e-6


@pytest.mark.parametrize("level", range(10))
@pytest.mark.parametrize("strategy", sorted(writers.STRATEGIES))
def test_reference_decoder(level, strategy):
    data = TEXT[:6000] + NOISE[:300] + b"a" * 700
    c = zlib.compressobj(level, zlib.DEFLATED, -15, 1 + level % 9, writers.STRATEGIES[strategy])
    z = c.compress(data) + c.flush()
    out, blocks, final = deflate_ref.decode(z)
    assert final and out.astype(np.uint8).tobytes() == data and sum(b.out_len for b in blocks) == len(data)


@given(st.binary(max_size=200), st.binary(max_size=3000))
@settings(max_examples=50, deadline=None)
def test_crc_of_concatenation(a, b):
    assert crc.combine(zlib.crc32(a), zlib.crc32(b), len(b)) == zlib.crc32(a + b)


def _file(data: bytes, mem: int = 8) -> tuple[bytes, list]:
    c = zlib.compressobj(6, zlib.DEFLATED, 31, mem)
    z = c.compress(data) + c.flush()
    return z, deflate_ref.list_blocks(z, 80)


def test_twin_decoding_and_splices():
    data = TEXT[:150_000] + NOISE[:60_000] + TEXT[150_000:250_000]
    z, blocks = _file(data, 5)
    starts = [b for b in blocks if not b.final and b.kind != "fixed"]
    assert {b.kind for b in starts} == {"dynamic", "stored"}
    for b, c in zip(starts[::3], starts[3::3], strict=False):
        end = c.start_bit if c.kind == "dynamic" else ((c.start_bit + 3 + 7) // 8) * 8 - 3
        d = probe.decode_span(z, b.start_bit, end, end_kind=c.kind)
        assert d.ok, d.reason
        ref = deflate_ref.decode(z, b.start_bit, c.start_bit, marked=True)[0]
        assert np.array_equal(np.concatenate([probe.symbols(p) for p in d.pieces]), ref)
        at = sum(x.out_len for x in blocks if x.start_bit < b.start_bit)
        window = data[max(0, at - 32768) : at]
        assert b"".join(probe.apply(p, window) for p in d.pieces) == data[at : at + d.out_len]
        assert probe.step(probe.tail_map(d), window) == data[: at + d.out_len][-32768:].rjust(32768, b"\0")
    true = {b.start_bit for b in blocks}
    first = starts[0].start_bit
    wrong = [e for e in random.sample(range(first + 50, 8 * len(z) - 200), 150) if e not in true]
    assert not any(probe.ends_at(z, first, e) for e in wrong)


def test_streams_hold_little_and_equal_the_whole():
    """Dense and long spans come in parts of bounded size; what stage 1 keeps equals what the whole gives."""
    data = b"\0" * 30_000_000 + TEXT * 8 + NOISE * 3
    z = gzip.compress(data[:40_000_000], 6, mtime=0) + gzip.compress(data[40_000_000:], 6, mtime=0)
    blocks = deflate_ref.list_blocks(gzip.compress(TEXT * 8 + NOISE * 3, 6, mtime=0), 80)
    s = probe.SpanStream(lambda lo, n: z[lo : lo + n], len(z), 0, None, "member")
    sizes, got = [], []
    for p in s:
        sizes.append(len(p.data))
        got.append(p.data)
    assert s.ok and s.eof and max(sizes) <= probe.OUT_STEP and b"".join(got) == data
    y = gzip.compress(TEXT * 8 + NOISE * 3, 6, mtime=0)
    starts = [b for b in blocks if not b.final and b.kind == "dynamic"]
    for b, c, how in ((starts[1], starts[-1], True), (starts[2], starts[3], False), (starts[0], None, True)):
        end = c.start_bit if c else None
        d = probe.decode_span(y, b.start_bit, end, fallback=how)
        k = probe.Summary(probe.SpanStream(lambda lo, n: y[lo : lo + n], len(y), b.start_bit, end, fallback=how))
        assert d.ok and k.ok and (k.out_len, k.n_markers, k.last_marker, k.eof) == (d.out_len, d.n_markers, d.last_marker, d.eof)
        assert np.array_equal(k.tail_map(), probe.tail_map(d))
        assert [(x["n"], x["ends"], x["footer_crc"]) for x in k.pieces] == [(len(x.data), x.ends, x.crc) for x in d.pieces]
        assert all(x["crc"] in (-1, zlib.crc32(q.data)) for x, q in zip(k.pieces, d.pieces, strict=True))


def test_members_and_damage():
    z = gzip.compress(TEXT[:50_000], 6, mtime=0) + gzip.compress(b"", mtime=0) + gzip.compress(TEXT[:9000], mtime=0)
    d = probe.decode_span(z, 0, None, "member")
    assert d.ok and [len(p.data) for p in d.pieces] == [50_000, 0, 9000]
    assert [m[2] for m in gzipfmt.iter_members(z)] == [TEXT[:50_000], b"", TEXT[:9000]]
    assert not probe.decode_span(z[:-4], 0, None, "member").ok
    with pytest.raises(gzipfmt.ChecksumMismatch):
        list(gzipfmt.iter_members(z[:-5] + b"\0" + z[-4:]))
    with pytest.raises(gzipfmt.NotGzip):
        gzipfmt.parse_header(b"PK\3\4" + bytes(10))
    h = gzipfmt.parse_header(writers.bgzf(b"abc"))
    assert h.block_bytes == len(writers.bgzf(b"abc"))


def test_window_maps_compose():
    rng = np.random.default_rng(3)
    f, g, h = (np.where(rng.random(32768) < 0.5, rng.integers(0, 256, 32768), 32768 + rng.integers(0, 32768, 32768)).astype(np.uint16) for _ in range(3))
    w = rng.integers(0, 256, 32768).astype(np.uint8).tobytes()
    assert probe.step(probe.compose(f, g), w) == probe.step(g, probe.step(f, w))
    assert np.array_equal(probe.compose(probe.compose(f, g), h), probe.compose(f, probe.compose(g, h)))


def test_finders_agree_and_find_all():
    z, blocks = _file(TEXT, 5)
    true = {b.start_bit for b in blocks if b.kind == "dynamic" and not b.final}
    for variant in ("packed", "skip", "histset"):
        assert true <= set(finder.dynamic(z, variant=variant, confirm=512))
    part = next(iter(sorted(true)[1:]))
    for variant in ("zlib", "parser"):
        assert part in finder.dynamic(z, part - 300, part + 300, variant=variant, confirm=512)
    assert part in finder.dynamic(z, part - 300, part + 300, variant="text_only") or b"\xc3" in TEXT
    s = writers.gzip_member(NOISE, 0)
    lo, hi = finder.stored(s, 0, 8 * 20)[0]
    assert lo <= 80 <= hi


def test_cascade_rates_on_random_bits():
    n = 8 * len(NOISE)
    _, counts = finder.cascade(NOISE)
    for step, share in (("final_bit", 1 / 2), ("block_type", 3 / 8), ("literal_count", 1 / 128)):
        assert abs(counts[step] - n * share) < 6 * (n * share) ** 0.5
    reach = n * (1 / 8 - 1 / 128)
    assert abs(counts["precode_invalid"] - 0.6609 * reach) < 8 * (0.6609 * reach) ** 0.5


def test_cascade_reads_headers_at_once(monkeypatch):
    """the later checks take all headers with a usable precode side by side, and say of each what reading it alone says."""
    buf = NOISE[:60_000]
    alone, read = finder._lengths, []
    for start, end in ((0, None), (5, 8 * len(buf) - 3300), (8 * len(buf) - 900, None)):
        w = bits.words(buf)
        pos = finder.starts(buf, w, start, end or 8 * len(buf))
        pos = pos[finder._precode(w, pos, "leaves")[0]]
        for no_distances in (True, False):
            want = [alone(buf, p, no_distances) for p in pos.tolist()]
            for variant in ("packed", "skip", "histset"):
                monkeypatch.setattr(finder, "_lengths", lambda *a: read.append(a) or alone(*a))
                finder._last.clear()
                read.clear()
                found, counts = finder.cascade(buf, start, end, variant, no_distances)
                monkeypatch.setattr(finder, "_lengths", alone)
                assert found == [p for p, step in zip(pos.tolist(), want) if step == "accepted"]
                assert {k: n for k, n in counts.items() if k in want} == {k: want.count(k) for k in set(want)}
                assert len(pos) < 100 or len(read) < len(pos) / 2


def test_skip_walk_and_lookup_find_the_same():
    z, _ = _file(TEXT, 5)
    for buf in (NOISE[:5000], z[:5000], bytes(500), bytes([4]) * 500, b"\x14" * 77, b"\x00", b""):
        w = bits.words(buf)
        for start, end in ((0, 8 * len(buf)), (3, 8 * len(buf) - 5), (7, 7), (13, 14)):
            if start <= end <= 8 * len(buf):
                assert finder.starts(buf, w, start, end, "skip").tolist() == finder.starts(buf, w, start, end).tolist()
    for method in ("plain", "counters", "histset"):
        w = bits.words(NOISE[:20_000])
        pos = np.arange(8 * 19_900)
        assert [a.tolist() for a in finder._precode(w, pos, method)] == [a.tolist() for a in finder._precode(w, pos, "leaves")]


def test_single_dynamic_block_has_nothing_to_find():
    z = writers.single_dynamic_block(TEXT[:20_000])
    assert gzip.decompress(z) == TEXT[:20_000]
    assert [b.kind for b in deflate_ref.list_blocks(z, 80)] == ["dynamic"]


def test_prefetch_strategies():
    assert prefetch.adaptive([5], 4, 100) == [6, 7, 8, 9]
    assert prefetch.adaptive([1, 2, 50, 51], 4, 100) == [52, 53, 3, 4]
    assert prefetch.adaptive([9, 3, 7], 4, 100) == []
    assert prefetch.single([1, 2, 3], 8, 100) == [4, 5, 6, 7]
    assert prefetch.fixed([98], 4, 100) == [99]
    seq = prefetch.replay_one(list(range(50)), "adaptive", 4)
    assert seq["misses"] == 1 and seq["hits"] == 49
    assert prefetch.replay_one(list(range(50)), "none")["hits"] == 0


def test_measures():
    assert abs(measures.serial_rate(43.1, 301.8) - 37.7) < 0.05
    assert measures.bandwidth(10_000_000, [1.0, 2.0])["mb_s"] == 7.5


def test_catalogue_is_listed_without_a_session():
    import subprocess
    import sys
    from pathlib import Path

    root = Path(__file__).resolve().parent.parent
    code = "import __spark_entry__ as e; from pyspark.sql import SparkSession; assert SparkSession.getActiveSession() is None; assert set(e.oracle_sql()) <= set(e.queries())"
    done = subprocess.run([sys.executable, "-c", code], cwd=root, capture_output=True, text=True)
    assert done.returncode == 0, done.stderr[-2000:]
