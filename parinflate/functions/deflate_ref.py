"""A plain Deflate decoder: the oracle of the twin decoder, block listing and inspection. Slow by design; not on the main path."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from parinflate.functions import huffman
from parinflate.functions.bits import BitReader
from parinflate.functions.gzipfmt import CorruptBlock

WINDOW = 32768
MARKER = 32768
#: Fixed values of the format.
PRECODE_ORDER = (16, 17, 18, 0, 8, 7, 9, 6, 10, 5, 11, 4, 12, 3, 13, 2, 14, 1, 15)
KINDS = ("stored", "fixed", "dynamic", "reserved")


def _bases(first: int, step: int, n: int) -> tuple[list[int], list[int]]:
    """Base values and extra bits of symbols that come ``step`` to each count of extra bits, after a first run without."""
    base, extra, v = [], [], first
    for k in range(n):
        e = max(0, k // step - 1)
        base.append(v)
        extra.append(e)
        v += 1 << e
    return base, extra


LEN_BASE, LEN_EXTRA = _bases(3, 4, 28)
LEN_BASE, LEN_EXTRA = [*LEN_BASE, 258], [*LEN_EXTRA, 0]
DIST_BASE, DIST_EXTRA = _bases(1, 2, 30)


@dataclass
class DeflateBlock:
    start_bit: int
    end_bit: int
    kind: str
    final: bool
    out_len: int
    detail: dict = field(default_factory=dict)


def code_lengths(r: BitReader) -> tuple[list[int], list[int], dict]:
    """Lengths of the literal and distance codes of a dynamic block, after its type bits."""
    hlit, hdist, hclen = r.read(5), r.read(5), r.read(4)
    pre = [0] * 19
    for k in range(hclen + 4):
        pre[PRECODE_ORDER[k]] = r.read(3)
    if huffman.classify(pre) != huffman.VALID:
        raise CorruptBlock("precode")
    table, lens, want = huffman.build(pre), [], hlit + 257 + hdist + 1
    while len(lens) < want:
        s = table.decode(r)
        if s < 16:
            lens.append(s)
        elif s == 16:
            if not lens:
                raise CorruptBlock("repeat without a length")
            lens += [lens[-1]] * (3 + r.read(2))
        else:
            lens += [0] * (3 + r.read(3) if s == 17 else 11 + r.read(7))
    if len(lens) > want:
        raise CorruptBlock("repeat beyond the lengths")
    return lens[: hlit + 257], lens[hlit + 257 :], {"hlit": hlit, "hdist": hdist, "hclen": hclen, "precode": pre}


FIXED = ([8] * 144 + [9] * 112 + [7] * 24 + [8] * 8, [5] * 30)


def decode(buf: bytes, start_bit: int = 0, stop_bit: int | None = None, window: bytes | None = None, marked: bool = False, max_blocks: int | None = None, stop_kinds: tuple[str, ...] = ("dynamic", "stored")) -> tuple[np.ndarray, list[DeflateBlock], bool]:
    """(16-bit symbols, blocks, whether a final block ended it). With ``marked`` the unknown history is markers: flag bit and place.

    Decoding stops at the first block of ``stop_kinds``, not final, that starts at ``stop_bit`` or after it.
    """
    out = [MARKER + k for k in range(WINDOW)] if marked else list((window or b"")[-WINDOW:])
    skip, listed = len(out), []
    r = BitReader(buf, start_bit)
    while True:
        begin = r.pos
        final, kind = r.read(1), KINDS[r.read(2)]
        if stop_bit is not None and begin >= stop_bit and not final and kind in stop_kinds and begin > start_bit or max_blocks is not None and len(listed) >= max_blocks:
            return np.array(out[skip:], np.uint16), listed, False
        before, detail = len(out), {}
        if kind == "stored":
            r.align()
            n, inverse = r.read(16), r.read(16)
            if n ^ inverse != 0xFFFF:
                raise CorruptBlock("stored length")
            p = r.pos >> 3
            if p + n > len(buf):
                raise EOFError
            out += buf[p : p + n]
            r.seek(8 * (p + n))
        elif kind == "reserved":
            raise CorruptBlock("reserved type")
        else:
            if kind == "fixed":
                lit, dist = FIXED
            else:
                lit, dist, detail = code_lengths(r)
                if not lit[256] or huffman.classify(lit) != huffman.VALID or huffman.classify(dist) not in (huffman.VALID, huffman.EMPTY):
                    raise CorruptBlock("codes")
            lit_t, dist_t = huffman.build(lit), huffman.build(dist)
            while True:
                s = lit_t.decode(r)
                if s < 256:
                    out.append(s)
                elif s == 256:
                    break
                else:
                    if s > 285:
                        raise CorruptBlock("length symbol")
                    n = LEN_BASE[s - 257] + r.read(LEN_EXTRA[s - 257])
                    d = dist_t.decode(r)
                    if d > 29:
                        raise CorruptBlock("distance symbol")
                    far = DIST_BASE[d] + r.read(DIST_EXTRA[d])
                    if far > len(out):
                        raise CorruptBlock("distance beyond the window")
                    for _ in range(n):
                        out.append(out[-far])
        listed.append(DeflateBlock(begin, r.pos, kind, bool(final), len(out) - before, detail))
        if final:
            return np.array(out[skip:], np.uint16), listed, True


def list_blocks(buf: bytes, start_bit: int = 0) -> list[DeflateBlock]:
    return decode(buf, start_bit)[1]
