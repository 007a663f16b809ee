"""Huffman codes given as code lengths: validity, canonical tables."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

VALID, OVER, UNDER, EMPTY = "valid", "over", "under", "empty"


def classify(lens: list[int], single_ok: bool = True) -> str:
    """valid: every leaf is used (or the code is one symbol of length 1, if ``single_ok``); over: more codes than leaves; under: unused leaves."""
    used = [n for n in lens if n]
    if not used:
        return EMPTY
    top = max(used)
    total = sum(1 << (top - n) for n in used)
    if total > 1 << top:
        return OVER
    if total == 1 << top or single_ok and used == [1]:
        return VALID
    return UNDER


@dataclass
class DecodeTable:
    """``table[peeked bits]`` is symbol * 16 + length, or 0 for bits that are no code."""

    bits: int
    table: np.ndarray

    def decode(self, r) -> int:
        entry = int(self.table[r.peek(self.bits)])
        if not entry:
            raise ValueError("not a code")
        r.read(entry & 15)
        return entry >> 4


def build(lens: list[int]) -> DecodeTable:
    """Canonical codes: shorter first, then by symbol; bits of a code arrive most significant first."""
    top = max(lens, default=0) or 1
    table = np.zeros(1 << top, np.int32)
    code = 0
    for n in range(1, top + 1):
        for symbol, length in enumerate(lens):
            if length == n:
                if code >= 1 << n:
                    raise ValueError("oversubscribed code")
                back = int(format(code, f"0{n}b")[::-1], 2)
                table[back :: 1 << n] = symbol * 16 + n
                code += 1
        code <<= 1
    return DecodeTable(top, table)
