"""Word shingle sets as sorted arrays of 64-bit hashes, and their universal hash minima; numpy only, used inside Arrow functions."""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np
import xxhash

#: Word hashes that a worker keeps; the table starts anew when it is full.
CACHE = 300_000
WIDTH = 5
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= CACHE:
            self.clear()
        v = self[word] = xxhash.xxh64_intdigest(word)
        return v


_hashes = _Hashes()
clear = _hashes.clear


def words(text: bytes | None) -> list[bytes]:
    """Words of a text, A-Z in lower case; bytes.split and bytes.lower treat ASCII alone, as the definition asks."""
    return text.lower().split() if text else []


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * _M1
    h = (h ^ (h >> np.uint64(27))) * _M2
    return h ^ (h >> np.uint64(31))


def shingle_set(ws: list[bytes], width: int = WIDTH) -> np.ndarray:
    """Distinct shingles of ``width`` words; fewer words make one shingle of them all; no words make none."""
    n = len(ws)
    if not n:
        return np.empty(0, np.uint64)
    if n < width:
        return np.array([xxhash.xxh64_intdigest(b" ".join(ws), seed=n)], np.uint64)
    a = np.fromiter(map(_hashes.__getitem__, ws), np.uint64, n)
    h = np.zeros(n - width + 1, np.uint64)
    for k in range(width):
        h = mix(h + a[k : n - width + 1 + k])
    return np.unique(h)


def digest(ws: list[bytes]) -> bytes:
    return hashlib.blake2b(b" ".join(ws), digest_size=16).digest()


@lru_cache
def coefficients(n: int, seed: int = 11) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.Generator(np.random.PCG64(seed))
    return rng.integers(0, 2**63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1), rng.integers(0, 2**63, n, dtype=np.uint64)


def minima(s: np.ndarray, n: int) -> np.ndarray:
    """``n`` minima of multiply-and-add universal hashes, upper 32 bits of each; the set is folded in pieces so that memory stays bounded."""
    a, b = coefficients(n)
    out = np.full(n, 0xFFFFFFFF, np.uint32)
    for i in range(0, len(s), 4096):
        out = np.minimum(out, ((s[i : i + 4096, None] * a + b) >> np.uint64(32)).min(axis=0).astype(np.uint32))
    return out


def band_keys(sig: np.ndarray, rows: int) -> np.ndarray:
    """One 64-bit key per band of ``rows`` minima."""
    m = sig.reshape(-1, rows).astype(np.uint64)
    h = np.arange(len(m), dtype=np.uint64)
    for k in range(rows):
        h = mix(h * np.uint64(0x9E3779B97F4A7C15) + m[:, k])
    return h
