"""CRC32 of a concatenation from the parts' CRCs, by powers of the operator that appends zeros."""

from __future__ import annotations

from functools import lru_cache

POLY = 0xEDB88320


def _times(m: tuple[int, ...], v: int) -> int:
    out, k = 0, 0
    while v:
        if v & 1:
            out ^= m[k]
        v >>= 1
        k += 1
    return out


@lru_cache(maxsize=64)
def _zeros(log2_bytes: int) -> tuple[int, ...]:
    """The operator that appends 2^log2_bytes zero bytes."""
    if not log2_bytes:
        step = (POLY, *(1 << k for k in range(31)))  # one zero bit
        for _ in range(3):
            step = tuple(_times(step, x) for x in step)
        return step
    half = _zeros(log2_bytes - 1)
    return tuple(_times(half, x) for x in half)


def combine(crc1: int, crc2: int, len2: int) -> int:
    """CRC32 of a + b from CRC32(a), CRC32(b) and the length of b."""
    k = 0
    while len2:
        if len2 & 1:
            crc1 = _times(_zeros(k), crc1)
        len2 >>= 1
        k += 1
    return crc1 ^ crc2
