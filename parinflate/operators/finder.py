"""Block finders: where may a Deflate block begin? Stored blocks, dynamic blocks in several variants, members; combined and confirmed.

The dynamic cascade tests, in order: the final bit, the type, the count of literal codes, the precode, the lengths coded by it, the distance
code, the literal code. Offsets are bits of the buffer.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import lru_cache
from itertools import product

import numpy as np

from parinflate.functions import bits, deflate_ref, huffman
from parinflate.functions.gzipfmt import MAGIC, CorruptBlock, ParinflateError, parse_header
from parinflate.functions.probe import primed, twins

STEPS = ("final_bit", "block_type", "literal_count", "precode_invalid", "precode_unused", "precode_data", "distance_invalid", "distance_unused", "literal_invalid", "literal_unused", "accepted")
#: Published shares of random offsets that each step rejects, of 10^12.
PUBLISHED = {"final_bit": 500000.1e-6, "block_type": 375000.0e-6, "literal_count": 7812.47e-6, "precode_invalid": 77451.6e-6, "precode_unused": 39256.9e-6, "precode_data": 386.66e-6, "distance_invalid": 14.291e-6, "distance_unused": 77.126e-6, "literal_invalid": 340.6e-9, "literal_unused": 517.2e-9, "accepted": 202e-12}
VARIANTS = ("zlib", "parser", "text_only", "skip", "packed", "histset")
TEXT = (9, 126)


def stored(buf: bytes, start: int, end: int) -> np.ndarray:
    """(lo, hi) of every candidate for a stored block: any bit in [lo, hi] may be its first, as header and padding are all zero."""
    a = np.frombuffer(buf, np.uint8)
    if len(a) < 5:
        return np.empty((0, 2), np.int64)
    n = a[:-3].astype(np.uint32) | a[1:-2].astype(np.uint32) << 8
    inverse = a[2:-1].astype(np.uint32) | a[3:].astype(np.uint32) << 8
    k = np.flatnonzero((n ^ inverse) == 0xFFFF)
    k = k[k > 0]
    # Final bit and type are the three zero bits before the length or further down the padding.
    lead = a[k - 1]
    ok = lead >> 5 == 0
    k, lead = k[ok], lead[ok]
    hi = 8 * k - 3
    zeros = np.array([8 - int(x).bit_length() for x in lead], np.int64)
    lo = np.maximum(8 * k - zeros, 8 * k - 10)
    keep = (hi >= start) & (lo < end)
    return np.stack([lo[keep], hi[keep]], axis=1)


@lru_cache
def precode_table() -> np.ndarray:
    """For 20 bits of counters (lengths 1 to 4, five bits each): the leaves of 128 that are left, or -1 if there are too many codes."""
    v = np.arange(1 << 20, dtype=np.int64)
    left = 128 - sum(((v >> (5 * (k - 1))) & 31) << (7 - k) for k in range(1, 5))
    return np.where(left < 0, -1, left).astype(np.int16)


@lru_cache
def _long_leaves() -> np.ndarray:
    """For 15 bits of counters (lengths 5 to 7): how many leaves of 128 they use."""
    v = np.arange(1 << 15, dtype=np.int16)
    return sum(((v >> (5 * k)) & 31) << (2 - k) for k in range(3)).astype(np.int16)


@lru_cache
def valid_histograms() -> frozenset[int]:
    """Packed counters of every usable precode: complete ones of at most 19 codes, and the single code of one bit."""
    found = set()

    def grow(length: int, left: int, used: int, packed: int) -> None:
        if not left:
            found.add(packed)
        elif length <= 7:
            for n in range(min(left >> (7 - length), 19 - used) + 1):
                grow(length + 1, left - (n << (7 - length)), used + n, packed | n << (5 * length))

    grow(1, 128, 0, 0)
    return frozenset(found | {1 << 5})


@lru_cache
def _histogram_set() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The set of usable precodes for many lookups at once: a row for the counters of lengths 1 to 4, a column for those of 5 to 7, and whether both together are in the set."""
    known = np.array(sorted(h >> 5 for h in valid_histograms()), np.int64)
    short, rows = np.unique(known & 0xFFFFF, return_inverse=True)
    long, columns = np.unique(known >> 20, return_inverse=True)
    row, column = np.zeros(1 << 20, np.uint16), np.zeros(1 << 15, np.uint16)
    # Row and column 0 are those of counters that no usable precode has.
    row[short], column[long] = (1 + np.arange(len(short))) * (len(long) + 1), 1 + np.arange(len(long))
    usable = np.zeros((len(short) + 1, len(long) + 1), bool)
    usable[1 + rows, 1 + columns] = True
    return row, column, usable.ravel()


@lru_cache
def _four(method: str) -> np.ndarray:
    """For 12 bits, which are four lengths of three bits: packed counters (``counters``), or leaves of 128 they use and, 12 bits up, how many are not zero (``leaves``)."""
    v = np.arange(1 << 12, dtype=np.int64)
    lengths = [(v >> (3 * k)) & 7 for k in range(4)]
    if method == "counters":
        return sum(np.int64(1) << (5 * x) for x in lengths)
    return sum(np.where(x > 0, (128 >> x) + (1 << 12), 0) for x in lengths).astype(np.int32)


#: For a header's count of precode lengths, less four: the bits they take.
_LENGTHS = np.array([(1 << 3 * (4 + k)) - 1 for k in range(16)], np.uint64)


def _lengths_field(w: np.ndarray, pos: np.ndarray) -> np.ndarray:
    """The precode lengths of headers at ``pos`` as 57 bits; lengths beyond the header's count are zero."""
    return bits.at(w, pos + 17) & _LENGTHS.take((bits.at(w, pos + 13) & np.uint64(15)).view(np.int64))


def _summed(field: np.ndarray, table: np.ndarray) -> np.ndarray:
    field = field.view(np.int64)
    out = table.take(field & 0xFFF)
    for k in range(1, 5):
        out += table.take((field >> 12 * k) & 0xFFF)
    return out


def _precode(w: np.ndarray, pos: np.ndarray, method: str) -> tuple[np.ndarray, np.ndarray]:
    """(valid, oversubscribed) of the precodes at header offsets ``pos``, by one of four ways that agree."""
    field = _lengths_field(w, pos)
    if method == "leaves":
        t = _summed(field, _four("leaves"))
        used = t & 0xFFF
        return (used == 128) | (t == (1 << 12) + 64), used > 128
    if method == "plain":
        used = np.zeros(len(pos), np.uint16)
        for k in range(19):
            if k % 5 == 0:
                five = ((field >> np.uint64(3 * k)) & np.uint64(0x7FFF)).astype(np.uint16)
            x = (five >> np.uint16(3 * (k % 5))) & np.uint16(7)
            used += (np.uint16(128) >> x) & np.uint16(127)
        # Half the leaves may be those of one code, which needs the count of codes.
        valid, half = used == 128, np.flatnonzero(used == 64)
        codes = sum(((field[half] >> np.uint64(3 * k)) & np.uint64(7) > 0).astype(np.int64) for k in range(19))
        valid[half] = codes == 1
        return valid, used > 128
    packed = _summed(field, _four("counters")) >> 5
    short, long = packed & 0xFFFFF, packed >> 20
    left = precode_table().take(short) - _long_leaves().take(long)
    if method == "histset":
        row, column, usable = _histogram_set()
        return usable.take(row.take(short) + column.take(long)), left < 0
    return (left == 0) | (packed == 1), left < 0


_REVERSED = [int(format(k, "07b")[::-1], 2) for k in range(128)]


@lru_cache(maxsize=4096)
def _precode_codes(field: int) -> list[int]:
    """For seven peeked bits: symbol * 8 + length of a usable precode, or -1. Codes in order of length and symbol are runs of the values read the other way round."""
    order = sorted(((field >> (3 * k)) & 7, s) for k, s in enumerate(deflate_ref.PRECODE_ORDER) if (field >> (3 * k)) & 7)
    runs: list[int] = []
    for length, s in order:
        runs += [s * 8 + length] * (128 >> length)
    runs += [-1] * (128 - len(runs))
    return [runs[k] for k in _REVERSED]


def _lengths(buf: bytes, pos: int, no_distances: bool = True) -> str:
    """The step at which a header with a valid precode fails, or 'accepted'. A block of literals alone may have no distance code: one of no bits or, with ``no_distances``, several."""
    first = pos >> 3
    word = int.from_bytes(buf[first : first + 320], "little") >> (pos & 7)
    limit = 8 * (len(buf) - first) - (pos & 7)
    n_literal, want = ((word >> 3) & 31) + 257, ((word >> 3) & 31) + ((word >> 8) & 31) + 258
    n = ((word >> 13) & 15) + 4
    codes = _precode_codes((word >> 17) & ((1 << 3 * n) - 1))
    at = 17 + 3 * n
    word >>= at
    lens: list[int] = []
    while len(lens) < want:
        code = codes[word & 127]
        if code < 0:
            return "precode_data"
        size, s = code & 7, code >> 3
        word >>= size
        at += size
        if s < 16:
            lens.append(s)
            continue
        extra, least = ((2, 3), (3, 3), (7, 11))[s - 16]
        if s == 16 and not lens:
            return "precode_data"
        lens += [lens[-1] if s == 16 else 0] * (least + (word & ((1 << extra) - 1)))
        word >>= extra
        at += extra
    if len(lens) > want or at > limit:
        return "precode_data"
    kind = huffman.classify(lens[n_literal:])
    if kind == huffman.OVER or kind == huffman.EMPTY and not no_distances and len(lens) > n_literal + 1:
        return "distance_invalid"
    if kind == huffman.UNDER:
        return "distance_unused"
    kind = huffman.classify(lens[:n_literal])
    if kind == huffman.OVER:
        return "literal_invalid"
    if kind != huffman.VALID or not lens[256]:
        return "literal_unused"
    return "accepted"


#: Fewer headers than these are read one by one.
_FEW = 24


#: By symbol of a precode from 16 on: bits of its repeat, least run.
_REPEATS = np.array(((2, 3), (3, 3), (7, 11))).T
#: By length that a precode gives, which is its symbol: leaves of 2^15 and, 32 bits up, that there is a code; 0 for repeats of 0.
_WEIGHTS = np.array([(1 << 32) + (1 << 15 - s) if 0 < s < 16 else 0 for s in range(19)])
_NO_CODE = 255
#: Codes read of each header until those that are done with are left out.
_TURNS = 8


def _precode_tables(lens: np.ndarray) -> np.ndarray:
    """128 entries for each row of nineteen lengths by symbol, as of ``_precode_codes`` but in the order of values read the other way round; ``_NO_CODE`` for bits that are none."""
    key = np.sort(np.where(lens > 0, 32 * lens + np.arange(19), 1 << 10).astype(np.int16), axis=1)
    symbol, lens = key & 31, key >> 5
    runs = np.where(lens < 8, 128 >> lens, 0)
    entries = np.concatenate([8 * symbol + lens, np.full((len(lens), 1), _NO_CODE)], axis=1).astype(np.uint8)
    return np.repeat(entries.ravel(), np.concatenate([runs, 128 - runs.sum(axis=1, keepdims=True)], axis=1).ravel())


def _all_lengths(buf: bytes, pos: np.ndarray, no_distances: bool = True) -> list[str]:
    """:func:`_lengths` of many headers: one code of each is read at a time. The few whose distance code passes are read one by one."""
    out = np.full(len(pos), "", dtype="<U17")
    if len(pos) >= _FEW:
        # 64 bits at every fourth byte hold the 14 of a code and its repeat, wherever they begin.
        v = np.ndarray((len(buf) // 4 + 1,), "<i8", buf + bytes(12), 0, (4,)).copy()
        peek = lambda a: v.take(a >> 5, mode="clip") >> (a & 31)
        reversed_ = np.array(_REVERSED)
        head = peek(pos + 3)
        literals, n = (head & 31) + 257, ((head >> 10) & 15) + 4
        total = literals + ((head >> 5) & 31) + 1
        lens = np.zeros((len(pos), 19), np.int64)
        lens[:, list(deflate_ref.PRECODE_ORDER)] = np.where(np.arange(19) < n[:, None], peek((pos + 17)[:, None] + 3 * np.arange(19)) & 7, 0)
        # The last table is for headers that are done with until they are left out: no bits, no length.
        table = np.concatenate([_precode_tables(lens), np.zeros(128, np.uint8)])
        idle, never = 128 * len(pos), 1 << 30
        who, at, row = np.arange(len(pos)), pos + 17 + 3 * n, 128 * np.arange(len(pos))
        seen, distances, last, one = np.zeros_like(pos), np.zeros_like(pos), np.full_like(pos, -1), np.ones_like(pos)
        while len(who) >= _FEW:
            for _ in range(_TURNS):
                x = peek(at)
                code = table.take(row + reversed_.take(x & 127)).astype(np.int64)
                at += code & 7
                symbol, now, bad = code >> 3, seen + one, None
                if len(k := np.flatnonzero(code >= 16 * 8)):  # repeats, and bits that are no code
                    s, own = symbol[k], code[k]
                    bad = k[(own == _NO_CODE) | (s == 16) & (last[k] < 0)]
                    extra, least = (a.take(s - 16, mode="clip") for a in _REPEATS)
                    now[k] += least - 1 + ((x[k] >> (own & 7)) & (1 << extra) - 1)
                    at[k] += extra
                    symbol[k] = np.where(s == 16, last[k], 18)
                if len(k := np.flatnonzero(now > literals)):
                    distances[k] += _WEIGHTS.take(symbol[k]) * (now[k] - np.maximum(seen[k], literals[k]))
                seen, last = now, symbol
                if bad is not None:
                    seen[bad] = never - 1
                if len(k := np.flatnonzero(seen >= total)):
                    row[k], one[k] = idle, 0
                    total[k] += never
            k = np.flatnonzero(row == idle)
            out[who[k]] = "precode_data"
            k = k[(seen[k] == total[k] - never) & (at[k] <= 8 * len(buf))]
            leaves, codes = distances[k] & 0xFFFFFFFF, distances[k] >> 32
            many = (leaves > 1 << 15) | (codes == 0) & (total[k] - never > literals[k] + 1) & (not no_distances)
            few = (codes > 0) & (leaves < 1 << 15) & ((codes > 1) | (leaves != 1 << 14))
            out[who[k]] = np.where(many, "distance_invalid", np.where(few, "distance_unused", ""))
            going = np.flatnonzero(row < idle)
            who, at, row, seen, distances, last, one, literals, total = (a[going] for a in (who, at, row, seen, distances, last, one, literals, total))
    found = out.tolist()
    for k in np.flatnonzero(out == "").tolist():
        found[k] = _lengths(buf, int(pos[k]), no_distances)
    return found


_last: list = []


def _later_steps(buf: bytes, pos: np.ndarray, no_distances: bool) -> list[str]:
    """:func:`_all_lengths`, which knows no variants: where a variant found the very headers that the one before it found in the same buffer, they are not read again."""
    if not (_last and _last[0] is buf and _last[1] == no_distances and np.array_equal(_last[2], pos)):
        _last[:] = buf, no_distances, pos, _all_lengths(buf, pos, no_distances)
    return _last[3]


def starts(buf: bytes, w: np.ndarray, start: int, end: int, variant: str = "packed") -> np.ndarray:
    """Offsets in [start, end) that pass the first three checks: by the distances of the skip table one after the other (``skip``), or by one lookup per byte."""
    if variant == "skip":
        return _walked(w, start, end)
    lo, hi = start >> 3, min(len(w), (end + 7) >> 3)
    mask = bits.start_table().take((w[lo:hi] & np.uint64(0x1FFFFF)).view(np.int64))
    pos = np.flatnonzero(np.unpackbits(mask, bitorder="little").view(bool))
    return pos[slice(*np.searchsorted(pos, (start - 8 * lo, end - 8 * lo)))] + 8 * lo


#: Bits of the lanes that walk by the skip table side by side, and steps after which those at their ends are left out.
_LANE, _STEPS = 64, 8
_FOUND = 16


@lru_cache
def _steps() -> np.ndarray:
    """For each window of the skip table: the distance to the next offset to look at, from a find by the window's other bits; ``_FOUND`` more at a find."""
    far = bits.skip_table()
    n = len(far).bit_length() - 1
    # What lies behind the window is unknown and may be a header: the least of both ways to go on.
    rest = np.arange(len(far)) >> 1
    return np.where(far > 0, far, _FOUND + 1 + np.minimum(np.minimum(far[rest], far[rest | len(far) >> 1]), n - 1))


def _walked(w: np.ndarray, start: int, end: int) -> np.ndarray:
    """Offsets in [start, end) where the skip table's distance is 0: lanes of bits are walked by these distances side by side, and finds are marked."""
    table, low = _steps(), w.view(np.int64)
    # A lane that has come to its end marks what the next one marks as well, until it is left out.
    mark = np.zeros(max(0, end) + 16 * _STEPS, bool)
    at = np.arange(start, end, _LANE)
    to = np.minimum(at + _LANE, end)
    while len(at):
        for _ in range(_STEPS):
            step = table.take((low.take(at >> 3, mode="clip") >> (at & 7)) & 0x3FFF)
            mark[at] = step >= _FOUND
            at = at + (step & _FOUND - 1)
        going = np.flatnonzero(at < to)
        at, to = at[going], to[going]
    return np.flatnonzero(mark[: max(0, end)])


def first_counts(buf: bytes, start: int, end: int) -> dict[str, int]:
    """How many offsets in [start, end) each of the first three checks rejects, by Boolean algebra on 64 bits at a time."""
    piece, n, r = buf[start >> 3 : ((end + 7) >> 3) + 2], max(0, end - start), start & 7
    x = np.frombuffer(piece + bytes(24 - len(piece) % 8), "<u8")
    own = np.zeros(len(x) - 1, np.uint64)
    own[: n >> 6] = ~np.uint64(0)
    own[n >> 6] = np.uint64((1 << (n & 63)) - 1)
    at = lambda k: x[:-1] >> np.uint64(k + r) | x[1:] << np.uint64(63 - k - r) << np.uint64(1)
    going = own & ~at(0)
    typed = going & ~at(1) & at(2)
    many = typed & at(4) & at(5) & at(6) & at(7)
    ones = lambda a: int(np.bitwise_count(a).sum(dtype=np.int64))
    return {"final_bit": n - ones(going), "block_type": ones(going) - ones(typed), "literal_count": ones(many)}


#: How each variant tests precodes.
PRECODE = {"packed": "counters", "skip": "plain", "histset": "histset", "text_only": "plain", "leaves": "leaves"}


#: Bytes whose offsets a cascade tests at a time, so that its arrays stay in a core's cache.
_BLOCK = 128 << 10


def cascade(buf: bytes, start: int = 0, end: int | None = None, variant: str = "packed", no_distances: bool = True) -> tuple[list[int], dict[str, int]]:
    """(accepted offsets, rejections by step) over bit offsets [start, end). The published shares count a header without distance codes as invalid, unless it has one of no bits."""
    end = min(8 * len(buf), end if end is not None else 8 * len(buf))
    counts = dict.fromkeys(("final_bit", "block_type", "literal_count", "passed", "precode_invalid", "precode_unused"), 0)
    usable = [np.empty(0, np.int64)]
    for lo in range(start, end, 8 * _BLOCK):
        hi, base = min(end, lo + 8 * _BLOCK), lo >> 3 << 3
        w = bits.words(buf[lo >> 3 : ((hi + 7) >> 3) + 16])
        pos = starts(buf, w, lo - base, hi - base, variant)
        valid, over = _precode(w, pos, PRECODE[variant])
        n_over, n_valid = int(np.count_nonzero(over)), int(np.count_nonzero(valid))
        for step, n in (first_counts(buf, lo, hi) | {"passed": len(pos), "precode_invalid": n_over, "precode_unused": len(pos) - n_over - n_valid}).items():
            counts[step] += n
        usable.append(pos.take(np.flatnonzero(valid)) + base)
    pos = np.concatenate(usable)
    at = _later_steps(buf, pos, no_distances)
    for step in at:
        counts[step] = counts.get(step, 0) + 1
    return [p for p, step in zip(pos.tolist(), at) if step == "accepted"], counts


#: Bytes of input for the library's first look at a header.
_LOOK = 400


def _trial(buf: bytes, pos: int, least: int, text: bool = False) -> bool:
    """Whether inflating at ``pos`` gives ``least`` bytes or reaches a clean end, of text bytes only if asked. The library refuses most false headers at a first look."""
    d = zlib.decompressobj(-15, zdict=twins()[0])
    try:
        d.decompress(primed(buf, pos, (pos >> 3) + _LOOK), 1)
        data = primed(buf, pos, (pos >> 3) + (64 << 10))
        d = zlib.decompressobj(-15, zdict=twins()[0])
        out = d.decompress(data, least)
    except zlib.error:
        return False
    if not (len(out) >= least or d.eof or 8 * len(buf) < pos + 64 * 8 * 1024 and len(out) > 0):
        return False
    if text:
        # Bytes that differ after another history are unknown; the others must be text.
        other = zlib.decompressobj(-15, zdict=twins()[1]).decompress(data, least)
        a, b = np.frombuffer(out, np.uint8), np.frombuffer(other, np.uint8)
        own = a[a == b]
        return bool(((own >= TEXT[0]) & (own <= TEXT[1])).all())
    return True


def _dynamic_start(buf: bytes, p: int) -> bool:
    return (buf[p >> 3] | (buf[(p >> 3) + 1] << 8 if (p >> 3) + 1 < len(buf) else 0)) >> (p & 7) & 7 == 4


def dynamic(buf: bytes, start: int = 0, end: int | None = None, variant: str = "packed", confirm: int = 0) -> list[int]:
    """Candidates for dynamic blocks by the named variant.

    ``zlib`` inflates at every bit, whatever is there, and asks for the type only of what inflates; ``parser`` reads the header at every
    bit and returns early; the others test the first checks and precodes in bulk. With ``confirm`` the library, which refuses
    what the later checks refuse, looks at what has a valid precode and must give so many bytes.
    """
    end = min(8 * len(buf), end if end is not None else 8 * len(buf))
    if variant == "zlib":
        return [p for p in range(start, end) if _trial(buf, p, max(1, confirm)) and _dynamic_start(buf, p)]
    if variant == "parser":
        found = [p for p in range(start, end) if _parsed(buf, p)]
        return [p for p in found if not confirm or _trial(buf, p, confirm)]
    if not confirm and variant != "text_only":
        return cascade(buf, start, end, variant)[0]
    w = bits.words(buf[start >> 3 : (end + 7) // 8 + 16])
    base = start >> 3 << 3
    pos = starts(buf, w, start - base, end - base, variant)
    pos = pos[_precode(w, pos, "leaves" if variant == "packed" else PRECODE[variant])[0]] + base
    if variant == "text_only":
        return [p for p in pos.tolist() if _trial(buf, p, max(confirm, 1024), text=True)]
    return [p for p in pos.tolist() if _trial(buf, p, confirm)]


def _parsed(buf: bytes, pos: int) -> bool:
    """The own parser with early return: type, counts, precode, then the lengths."""
    first = pos >> 3
    word = int.from_bytes(buf[first : first + 11], "little") >> (pos & 7)
    if word & 7 != 4 or (word >> 3) & 31 >= 30:
        return False
    n = ((word >> 13) & 15) + 4
    lens = [(word >> (17 + 3 * k)) & 7 for k in range(n)]
    return huffman.classify(lens) == huffman.VALID and _lengths(buf, pos) == "accepted"


def members(buf: bytes, start: int = 0, end: int | None = None) -> Iterator[int]:
    """Byte-aligned bit offsets of headers."""
    k = max(0, (start + 7) >> 3) - 1
    stop = (end if end is not None else 8 * len(buf)) >> 3
    while 0 <= (k := buf.find(MAGIC, k + 1)) < stop:
        try:
            parse_header(buf, k)
        except ParinflateError:
            continue
        yield 8 * k


def follow_stored(buf: bytes, lo: int, final: bool = False) -> bool:
    """Whether what follows a stored candidate's payload is the header of a block, or unknown: beyond a buffer that is not the file's end (``final``)."""
    p = (lo + 3 + 7) >> 3
    n = int.from_bytes(buf[p : p + 2], "little")
    q = p + 4 + n
    if q >= len(buf):
        return not final
    kind = (buf[q] >> 1) & 3
    if kind == 3:
        return False
    if kind == 0:
        return len(buf) < q + 5 or int.from_bytes(buf[q + 1 : q + 3], "little") ^ int.from_bytes(buf[q + 3 : q + 5], "little") == 0xFFFF
    return kind == 1 or _trial(buf, 8 * q, 64)


def candidates(buf: bytes, start: int = 0, end: int | None = None, confirm: int = 1024, variant: str = "packed", step: int = 1 << 14, final: bool = False) -> Iterator[tuple[int, int, str]]:
    """(first bit, last bit that means the same, kind) of confirmed candidates in order, searched ``step`` bytes at a time and more from step to step."""
    end = min(8 * len(buf), end if end is not None else 8 * len(buf))
    at = start
    while at < end:
        to = min(end, at + 8 * step)
        step = min(2 * step, 1 << 18)
        found = [(p, p, "dynamic") for p in dynamic(buf, at, to, variant, confirm)]
        lo_byte = max(0, (at >> 3) - 2)
        piece = buf[lo_byte : (to >> 3) + 8]
        found += [(int(a) + 8 * lo_byte, int(b) + 8 * lo_byte, "stored") for a, b in stored(piece, at - 8 * lo_byte, to - 8 * lo_byte) if follow_stored(buf, int(b) + 8 * lo_byte, final)]
        found += [(p, p, "member") for p in members(buf, at, to)]
        yield from sorted(x for x in found if at <= x[1] and x[0] < to)
        at = to


def random_precodes() -> dict[str, float]:
    """Exact shares of precodes of random bits: oversubscribed, with unused leaves, usable; averaged over the sixteen counts of lengths."""
    out = {"over": 0.0, "under": 0.0, "valid": 0.0}
    for n in range(4, 20):
        ways = {(0, 0): 1.0}  # (leaves used of 128, codes that are one single code of length 1)
        for _ in range(n):
            more: dict[tuple[int, int], float] = {}
            for ((used, single), p), length in product(ways.items(), range(8)):
                add = 0 if length == 0 else 128 >> length
                state = (min(129, used + add), 1 if length == 1 and used == 0 else (single if length == 0 else 2))
                more[state] = more.get(state, 0.0) + p / 8
            ways = more
        for (used, single), p in ways.items():
            kind = "over" if used > 128 else "valid" if used == 128 or used == 64 and single == 1 else "under"
            out[kind] += p / 16
    return out
