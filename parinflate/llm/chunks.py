"""Cutting texts where byte-level tokenizers cannot tell the parts from the whole.

The pattern of these tokenizers lets one space lead a word. Before a space that a non-space follows, no match can run on: what is
left of it ends there, or is white space that the pattern ends there, too. So a text is the chunk before its first such space and
chunks that each begin with a space, and the tokens of the text are those of its chunks.

A long stretch without such spaces has other safe places: no match runs from a non-space into white space, nor from a letter
to a digit or back.
"""

from __future__ import annotations

import re

import regex

#: Code points of a chunk from which on the other safe places are looked for.
LONG = 1 << 14

_UNSAFE = re.compile(r" (?=\s|\Z)")
_SAFE = re.compile(r" (?=\S)")
_INNER = regex.compile(r"(?<=\S)(?=\s)|(?<=\p{L})(?=\p{N})|(?<=\p{N})(?=\p{L})")


def chunks(text: str) -> list[str]:
    """The chunks of a text; all but the first lack the space that leads them."""
    return _SAFE.split(text) if _UNSAFE.search(text) else text.split(" ")


def pieces(chunk: str, most: int = LONG) -> list[str]:
    """A chunk as runs of about ``most`` code points, cut at the other safe places; a stretch without any stays whole."""
    if len(chunk) <= most:
        return [chunk]
    out, at, last = [], 0, 0
    for m in _INNER.finditer(chunk):
        k = m.start()
        if k - at >= most and last > at:
            out.append(chunk[at:last])
            at = last
        last = k
    if last > at and len(chunk) - at > most:
        out.append(chunk[at:last])
        at = last
    return [*out, chunk[at:]]
