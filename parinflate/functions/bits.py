"""Bits, least significant first: a reader, bulk windows at every offset, realignment and packed counters."""

from __future__ import annotations

from functools import lru_cache

import numpy as np


class BitReader:
    """Reads up to 64 bits per call from any bit."""

    def __init__(self, buf: bytes, start_bit: int = 0):
        self.buf, self.pos, self.end = buf, start_bit, 8 * len(buf)

    def peek(self, n: int) -> int:
        """The next ``n`` bits; bits beyond the end count as zero."""
        first = self.pos >> 3
        word = int.from_bytes(self.buf[first : first + (n + 14) // 8], "little")
        return (word >> (self.pos & 7)) & ((1 << n) - 1)

    def read(self, n: int) -> int:
        if self.pos + n > self.end:
            raise EOFError(f"{n} bits at {self.pos} of {self.end}")
        v = self.peek(n)
        self.pos += n
        return v

    def seek(self, bit: int) -> None:
        self.pos = bit

    def align(self) -> None:
        self.pos = (self.pos + 7) & ~7


def words(buf: bytes) -> np.ndarray:
    """The 64-bit word at every byte offset; bytes beyond the end are zero."""
    return np.ndarray((len(buf),), "<u8", buf + bytes(8), 0, (1,)).copy()


def windows(buf: bytes, nbits: int) -> np.ndarray:
    """The ``nbits`` (at most 57) bits at every bit offset, in order."""
    if nbits > 57:
        raise ValueError("a window has at most 57 bits")
    w = words(buf)
    return ((w[:, None] >> np.arange(8, dtype=np.uint64)) & np.uint64((1 << nbits) - 1)).ravel()


def at(w: np.ndarray, bits: np.ndarray) -> np.ndarray:
    """The 57 bits or more at the given bit offsets of ``words``."""
    return w.take(bits >> 3, mode="clip") >> (bits & 7).astype(np.uint64)


def realign(buf: bytes, start_bit: int, end_bit: int) -> bytes:
    """Bits [start_bit, end_bit) as bytes from bit 0; the rest of the last byte is zero."""
    if end_bit <= start_bit:
        return b""
    first, last, r = start_bit >> 3, (end_bit + 7) >> 3, start_bit & 7
    a = np.frombuffer(buf, np.uint8, last - first, first)
    if r:
        out = a >> r
        out[:-1] |= a[1:] << (8 - r)
    else:
        out = a.copy()
    n = (end_bit - start_bit + 7) >> 3
    out = out[:n]
    if spare := (8 * n) - (end_bit - start_bit):
        out[-1] &= 0xFF >> spare
    return out.tobytes()


def packed_add(counters: int, symbol: int, width: int = 5) -> int:
    """One more of ``symbol`` in counters of ``width`` bits each."""
    return counters + (1 << (width * symbol))


def unpack(counters: int, n: int = 8, width: int = 5) -> list[int]:
    return [(counters >> (width * k)) & ((1 << width) - 1) for k in range(n)]


@lru_cache
def skip_table(bits: int = 14) -> np.ndarray:
    """For each window of ``bits`` bits: the distance to the next offset that may be a dynamic, non-final header; 0: here."""
    v = np.arange(1 << bits, dtype=np.int64)
    skip = np.full(1 << bits, bits, np.int64)
    for d in range(bits - 1, -1, -1):
        x, seen = v >> d, bits - d
        ok = (x & 1) == 0
        if seen >= 2:
            ok &= ((x >> 1) & 1) == 0
        if seen >= 3:
            ok &= ((x >> 2) & 1) == 1
        if seen >= 8:
            ok &= ((x >> 3) & 31) < 30
        skip[ok] = d
    return skip


@lru_cache
def start_table() -> np.ndarray:
    """For the 21 bits from a byte on: bit r is set if a dynamic, non-final header may begin r bits further. One lookup tests eight offsets."""
    here = skip_table() == 0
    v = np.arange(1 << 21, dtype=np.int32)
    out = np.zeros(1 << 21, np.uint8)
    for r in range(8):
        out |= here[(v >> r) & 0x3FFF].astype(np.uint8) << r
    return out
