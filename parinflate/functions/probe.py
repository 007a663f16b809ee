"""Decoding a span of Deflate bits with the standard library: with a known history, or with two invented ones.

Twin dictionaries: inflate the span twice, after histories that differ at every place and whose pairs of bytes name the place. Bytes
that do not come from the history are equal in both results; an unequal pair is a marker for its place in the unknown window.

Splice test: a span [s, e) ends at a block boundary if its bits, an empty final block and a sentinel inflate to the end and leave just
the sentinel. Before a stored block, whose first bit padding hides, its own header with no content is fed as well, and a copy of the
inflate must give back the content of a stored block.

Priming: the library begins at a byte, so a start inside a byte is led by an empty dynamic block that fills whole bytes up to that bit.
Bytes of the file keep their boundaries, which stored blocks and footers go by.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np

from parinflate.functions.gzipfmt import CorruptBlock, ParinflateError, Truncated, parse_footer, parse_header

WINDOW = 32768
FLAG = 32768
SENTINEL = b"\xff" * 8
#: What closes a span before a stored block, whose length comes next: an empty one, an empty final block and the sentinel.
STORED_TAIL = b"\0\0\xff\xff\x03\0" + SENTINEL
#: A stored block's length and content that no code in the middle of a block decodes to.
_PROOF = hashlib.sha256(b"stored").digest()
STORED_PROOF = len(_PROOF).to_bytes(2, "little") + (len(_PROOF) ^ 0xFFFF).to_bytes(2, "little") + _PROOF
_NONE = np.empty(0, np.int64)


@lru_cache
def twins() -> tuple[bytes, bytes, np.ndarray]:
    """Two histories and the table from a pair of bytes (a + 256 b) to the place that it names."""
    i = np.arange(WINDOW)
    a, b = i % 256, (i + 1 + i // 256) % 256
    place = np.full(1 << 16, -1, np.int32)
    place[a + 256 * b] = i
    return a.astype(np.uint8).tobytes(), b.astype(np.uint8).tobytes(), place


@lru_cache
def primer(residue: int) -> bytes:
    """An empty, non-final dynamic block of a length that is ``residue`` modulo 8, the last byte unfinished.

    Its literal code is 256 codes of eight bits for symbols 1 to 256; the precode has one, two and two bits for repeat, zero and eight, and as
    many zero lengths after them as the length asks for.
    """
    for n in range(5, 13):
        fields = [(0, 1), (2, 2), (0, 5), (0, 5), (n - 4, 4)]
        fields += [({0: 1, 3: 2, 4: 2}.get(k, 0), 3) for k in range(n)]
        # Canonical codes, first bit lowest: repeat 0; zero 10; eight 11.
        zero, eight, again = (1, 2), (3, 2), (0, 1)
        fields += [zero, eight]
        for count in [6] * 42 + [3]:
            fields += [again, (count - 3, 2)]
        fields += [zero, (255, 8)]
        if sum(w for _, w in fields) % 8 == residue:
            value = at = 0
            for v, w in fields:
                value |= v << at
                at += w
            return value.to_bytes((at + 7) // 8, "little")
    raise AssertionError(residue)


def primed(buf: bytes, start_bit: int, end_byte: int) -> bytes:
    """Input for the library that begins at ``start_bit`` of ``buf`` and ends before ``end_byte``."""
    k, r = start_bit >> 3, start_bit & 7
    if not r:
        return buf[k:end_byte]
    lead = primer(r)
    if k >= end_byte:
        return lead[:-1]
    return b"".join((lead[:-1], bytes([lead[-1] | buf[k] >> r << r]), buf[k + 1 : end_byte]))


def closed(buf: bytes, start_bit: int, end_bit: int, before_stored: bool = False) -> bytes:
    """Input for the splice test of [start_bit, end_bit)."""
    if before_stored:
        return primed(buf, start_bit, (end_bit + 3) >> 3) + STORED_TAIL
    k, r = end_bit >> 3, end_bit & 7
    if not r:
        return primed(buf, start_bit, k) + b"\x03\0" + SENTINEL
    cut = buf[: k + 1] if start_bit >> 3 == k else buf
    whole = primed(cut, start_bit, k + 1)
    tail = whole[-1] & ((1 << r) - 1) | 3 << r
    return whole[:-1] + tail.to_bytes(2 if r <= 6 else 3, "little") + SENTINEL


@dataclass
class Piece:
    """What a span holds of one member."""

    data: bytes
    places: np.ndarray  # of bytes that are markers
    markers: np.ndarray  # their places in the window
    ends: bool = False  # the member's end lies in the span
    crc: int = 0  # of its footer
    isize: int = 0


@dataclass
class Decoded:
    ok: bool
    end_bit: int = -1
    pieces: list[Piece] = field(default_factory=list)
    reason: str = ""
    eof: bool = False

    @property
    def out_len(self) -> int:
        return sum(len(p.data) for p in self.pieces)

    @property
    def n_markers(self) -> int:
        return sum(len(p.places) for p in self.pieces)

    @property
    def last_marker(self) -> int:
        p = self.pieces[0].places if self.pieces else np.empty(0)
        return int(p[-1]) if len(p) else -1


#: Bytes of input and of output that a stream holds at a time; input while both twins run.
IN_STEP, OUT_STEP, TWIN_STEP = 1 << 20, 8 << 20, 1 << 16


@dataclass
class Part:
    """Output of a stream: some bytes of a member, or with ``ends`` its end and footer."""

    data: bytes = b""
    places: np.ndarray = field(default_factory=lambda: _NONE)
    markers: np.ndarray = field(default_factory=lambda: _NONE)
    ends: bool = False
    crc: int = 0
    isize: int = 0


class SpanStream:
    """Decodes from ``start_bit`` (of a block, or of a member's header) and checks that a block or a member begins at ``end_bit``; None: the file's end.

    Iterating gives parts of bounded size, however long or dense the span is; then ``ok``, ``reason``, ``end_bit`` and ``eof`` say how it
    ended. Without ``window`` the history of the first member is unknown and becomes markers. ``read(offset, length)`` gives bytes of
    the file of ``size`` bytes; bits count from its start. ``end_kind`` stored: ``end_bit`` is the last bit that may begin the block,
    three before its length. With ``fallback`` the second twin stops, at byte ``fallback_at``, once the last window holds no marker.
    """

    def __init__(self, read: Callable[[int, int], bytes], size: int, start_bit: int, end_bit: int | None, kind: str = "block", end_kind: str = "block", window: bytes | None = None, container: str = "gzip", fallback: bool = True):
        self.read, self.size, self.start, self.end, self.kind, self.end_kind = read, size, start_bit, end_bit, kind, end_kind
        self.window, self.container, self.fallback = window, container, fallback
        self.ok, self.reason, self.end_bit, self.eof, self.fallback_at = False, "", start_bit, False, -1

    def _input(self, at: int, stop: int, spliced: bool, twin: list[bool]) -> Iterator[bytes]:
        """Input for the library from bit ``at``: primed, as it is in the file, and closed for the splice test."""
        first, last = at >> 3, stop >> 3
        if last - first <= TWIN_STEP:
            buf = self.read(first, last - first + 2)
            shift = 8 * first
            if spliced and self.end_kind == "stored":
                yield primed(buf, at - shift, ((stop + 3) >> 3) - first)
                yield STORED_TAIL
                return
            yield closed(buf, at - shift, stop - shift) if spliced else primed(buf, at - shift, ((stop + 7) >> 3) - first)
            return
        upto = ((stop + 3) >> 3 if self.end_kind == "stored" else last) if spliced else (stop + 7) >> 3
        k = first
        while k < upto:
            n = min(upto - k, TWIN_STEP if twin[0] and self.fallback else IN_STEP)
            part = self.read(k, n)
            if not part:
                return
            yield primed(part, at & 7, len(part)) if k == first else part
            k += len(part)
        if spliced and self.end_kind == "stored":
            yield STORED_TAIL
        elif spliced and not stop & 7:
            yield b"\x03\0" + SENTINEL
        elif spliced:
            r = stop & 7
            yield (self.read(last, 1)[0] & ((1 << r) - 1) | 3 << r).to_bytes(2 if r <= 6 else 3, "little") + SENTINEL

    def _member(self, at: int, stop: int, spliced: bool, history: bytes | None) -> Iterator[Part]:
        """Parts of what is left of a member from bit ``at``; returns (bytes of the library's input used, bytes after the end or None)."""
        ha, hb, place = twins()
        twin = [history is None]
        da = zlib.decompressobj(-15, zdict=ha if twin[0] else history) if twin[0] or history else zlib.decompressobj(-15)
        db = zlib.decompressobj(-15, zdict=hb)
        done, last, fed = 0, -1, 0
        source = self._input(at, stop, spliced, twin)
        for chunk in source:
            # In the middle of a block, the tail's ones may be its end code. A content that comes out as it goes in proves that the length is next.
            if chunk is STORED_TAIL and not _stored_next(da):
                return fed, None
            fed += len(chunk)
            todo = chunk
            while todo or da.unconsumed_tail:
                a = da.decompress(todo, OUT_STEP)
                places = markers = _NONE
                if twin[0]:
                    b = db.decompress(todo, OUT_STEP)
                    x, y = np.frombuffer(a, np.uint8), np.frombuffer(b, np.uint8)
                    places = np.flatnonzero(x != y)
                    if len(places):
                        markers = place[x[places].astype(np.int32) + 256 * y[places].astype(np.int32)]
                        if (markers < 0).any():
                            raise CorruptBlock("a pair that names no place")
                        last = done + int(places[-1])
                    if self.fallback and done + len(a) - 1 - last > WINDOW:
                        twin[0], self.fallback_at = False, done + len(a)
                done += len(a)
                if a:
                    yield Part(a, places, markers)
                todo = da.unconsumed_tail
                if da.eof or not a:
                    break
            if da.eof:
                # What the library has not used: of this chunk, and what a chunk that closes the span would add.
                rest = da.unused_data
                if spliced and len(rest) < len(SENTINEL):
                    rest += b"".join(source)
                    fed += len(rest) - len(da.unused_data)
                return fed, rest
        return fed, None

    def __iter__(self) -> Iterator[Part]:
        try:
            yield from self._parts()
        except (zlib.error, ParinflateError, ValueError, IndexError) as e:
            self.ok, self.reason = False, f"{type(e).__name__}: {e}"

    def _parts(self) -> Iterator[Part]:
        stop = 8 * self.size if self.end is None else self.end
        at, first = self.start, True
        while True:
            self.end_bit = at
            if at == stop and not (first and self.kind == "block"):
                self.ok, self.eof = True, self.end is None
                return
            known = not (first and self.kind == "block")
            if known:
                if self.container != "gzip":
                    self.ok, self.eof, self.reason = self.end is None, True, "" if self.end is None else "data after the stream"
                    return
                at += 8 * _header(self.read, at >> 3)
            history = b"" if known else self.window
            first = False
            if at > stop:
                self.reason = "a header crosses the end"
                return
            spliced = self.end is not None and self.end_kind != "member"
            fed, rest = yield from self._member(at, stop, spliced, history)
            if rest is None:
                self.reason = "no block ends at the end" if self.end is not None else "truncated"
                return
            if spliced and rest == SENTINEL:
                self.ok, self.end_bit = True, stop
                return
            # A final block: the footer begins at the next byte of the file.
            lead = len(primer(at & 7)) - 1 if at & 7 else 0
            foot = (at >> 3) + fed - len(rest) - lead
            if self.container != "gzip":
                yield Part(ends=True)
                at = 8 * (foot + (4 if self.container == "zlib" else 0))
                continue
            after = foot + 8
            if after > self.size:
                self.reason = "truncated footer"
                return
            crc, isize = parse_footer(self.read(foot, 8), 0)
            yield Part(ends=True, crc=crc, isize=isize)
            at = 8 * after
            if self.end is None and self._padding(after):
                self.ok, self.eof, self.end_bit = True, True, at
                return
            if at > stop:
                self.reason = "a member crosses the end"
                return

    def _padding(self, at: int) -> bool:
        """Whether nothing but zero bytes follows."""
        while at < self.size:
            part = self.read(at, IN_STEP)
            if part.strip(b"\0"):
                return False
            at += len(part) or 1
        return True


def _stored_next(d) -> bool:
    """Whether the length of a stored block is what this inflate reads next."""
    try:
        return d.copy().decompress(STORED_PROOF).endswith(_PROOF)
    except zlib.error:
        return False


def _header(read: Callable[[int, int], bytes], at: int) -> int:
    """Length of the member's header at byte ``at``; names and extra fields may be long."""
    n = 1 << 10
    while True:
        buf = read(at, n)
        try:
            return parse_header(buf, 0).end
        except Truncated:
            if len(buf) < n:
                raise
            n *= 8


def decode_span(buf: bytes, start_bit: int, end_bit: int | None, kind: str = "block", end_kind: str = "block", window: bytes | None = None, container: str = "gzip", fallback: bool = True, most: int | None = None) -> Decoded:
    """The whole of a span in memory, its members as pieces; see :class:`SpanStream`. Bits are counted in ``buf``."""
    s = SpanStream(lambda lo, n: buf[lo : lo + n], len(buf), start_bit, end_bit, kind, end_kind, window, container, fallback)
    pieces, open_, total = [], [], 0
    for p in s:
        total += len(p.data)
        if most is not None and total > most:
            return Decoded(False, s.end_bit, pieces, "more than max_out_bytes")
        open_.append(p)
        if p.ends:
            pieces.append(_joined(open_))
            open_ = []
    if open_ or s.ok and not pieces and kind == "block":
        pieces.append(_joined(open_))
    return Decoded(s.ok, s.end_bit, pieces, s.reason, s.eof)


def _joined(parts: list[Part]) -> Piece:
    at, places = 0, []
    for p in parts:
        places.append(p.places + at)
        at += len(p.data)
    last = parts[-1] if parts else Part()
    return Piece(b"".join(p.data for p in parts), np.concatenate(places) if places else _NONE, np.concatenate([p.markers for p in parts]) if parts else _NONE, last.ends, last.crc, last.isize)


class Summary:
    """What stage 1 keeps of a span: sizes, markers, checksums of pieces and the tail as a function of the window; no payload but for the last 32 KiB."""

    def __init__(self, s: SpanStream):
        self.out_len = self.n_markers = 0
        self.last_marker = -1
        self.pieces: list[dict] = []
        self.tail, self.members, fresh, n, crc, at = np.empty(0, np.uint16), 0, True, 0, 0, 0
        for p in s:
            if fresh:
                self.tail, n, crc, at, fresh = np.empty(0, np.uint16), 0, 0, 0, False
                self.members += 1
            if len(p.places):
                crc = -1
                self.n_markers += len(p.places)
                self.last_marker = at + int(p.places[-1])
            crc = zlib.crc32(p.data, crc) if crc >= 0 else -1
            n, at = n + len(p.data), at + len(p.data)
            self.out_len += len(p.data)
            if p.data:
                cut = max(0, len(p.data) - WINDOW)
                keep = p.places >= cut
                self.tail = np.concatenate([self.tail, symbols(Piece(p.data[cut:], p.places[keep] - cut, p.markers[keep]))])[-WINDOW:]
            if p.ends:
                self.pieces.append({"n": n, "crc": crc, "ends": True, "footer_crc": p.crc, "isize": p.isize})
                fresh = True
        if not fresh or s.ok and not self.members and s.kind == "block":
            self.pieces.append({"n": n, "crc": crc, "ends": False, "footer_crc": 0, "isize": 0})
            self.members = max(1, self.members)
        self.ok, self.reason, self.end_bit, self.eof, self.fallback_at = s.ok, s.reason, s.end_bit, s.eof, s.fallback_at

    def tail_map(self) -> np.ndarray:
        return _filled(self.tail, self.members > 1 or self.eof)


def replaced(symbols_: bytes, window: bytes) -> bytes:
    """Marker replacement of kept symbols: one gather from all bytes and the window."""
    table = np.concatenate([np.arange(256, dtype=np.uint8), np.frombuffer(window.rjust(WINDOW, b"\0"), np.uint8)])
    s = np.frombuffer(symbols_, np.uint16)
    return table[np.where(s >= FLAG, s - np.uint16(FLAG - 256), s)].tobytes()


def _filled(s: np.ndarray, whole: bool) -> np.ndarray:
    """The last 32768 symbols from fewer: what lies before them is the window's end, or zero where a member begins in the span."""
    if len(s) == WINDOW:
        return s
    before = np.zeros(WINDOW - len(s), np.uint16) if whole else (FLAG + np.arange(len(s), WINDOW)).astype(np.uint16)
    return np.concatenate([before, s])


def decode_marked(buf: bytes, start_bit: int, end_bit: int | None = None) -> np.ndarray:
    """16-bit symbols of a span: literals, or the flag bit and a place in the unknown window."""
    d = decode_span(buf, start_bit, end_bit)
    if not d.ok:
        raise CorruptBlock(d.reason)
    return np.concatenate([symbols(p) for p in d.pieces]) if d.pieces else np.empty(0, np.uint16)


def symbols(p: Piece | Part) -> np.ndarray:
    s = np.frombuffer(p.data, np.uint8).astype(np.uint16)
    s[p.places] = FLAG + p.markers
    return s


def inflate_known(buf: bytes, start_bit: int, end_bit: int | None, window: bytes, kind: str = "block", end_kind: str = "block", container: str = "gzip") -> Decoded:
    return decode_span(buf, start_bit, end_bit, kind, end_kind, window, container)


def ends_at(buf: bytes, start_bit: int, end_bit: int) -> bool:
    """Whether a block of the decode that begins at ``start_bit`` ends at ``end_bit``."""
    return decode_span(buf, start_bit, end_bit).ok


def apply(p: Piece | Part, window: bytes) -> bytes:
    """Marker replacement: gather from the window at marker places only."""
    if not len(p.places):
        return p.data
    out = np.frombuffer(p.data, np.uint8).copy()
    w = np.frombuffer(window.rjust(WINDOW, b"\0"), np.uint8)
    out[p.places] = w[p.markers]
    return out.tobytes()


def tail_map(d: Decoded) -> np.ndarray:
    """The last 32768 symbols after a span, as a function of the window before it; history before a member's start is zero."""
    p = d.pieces[-1] if d.pieces else Piece(b"", _NONE, _NONE)
    cut = max(0, len(p.data) - WINDOW)
    keep = p.places >= cut
    return _filled(symbols(Piece(p.data[cut:], p.places[keep] - cut, p.markers[keep])), len(d.pieces) > 1 or d.eof)


def step(m: np.ndarray, window: bytes) -> bytes:
    """The window after a span from the one before it."""
    w = np.frombuffer(window.rjust(WINDOW, b"\0"), np.uint8)
    return np.where(m >= FLAG, w[np.where(m >= FLAG, m - FLAG, 0)], m & 0xFF).astype(np.uint8).tobytes()


def compose(first: np.ndarray, then: np.ndarray) -> np.ndarray:
    """The map of two spans in a row."""
    marked = then >= FLAG
    return np.where(marked, first[np.where(marked, then - FLAG, 0)], then).astype(np.uint16)
