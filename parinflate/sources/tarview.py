"""TAR members inside compressed archives: headers by a walk over ranges, members by range reads."""

from __future__ import annotations

from collections.abc import Iterator

from parinflate.sources.reader import SeekableReader

BLOCK = 512


def members(stream: SeekableReader) -> Iterator[tuple[str, int, int]]:
    """(name, offset of the content, size): one read of 512 bytes per member, seeking over contents."""
    at = 0
    while True:
        stream.seek(at)
        h = stream.read(BLOCK)
        if len(h) < BLOCK or not h.strip(b"\0"):
            return
        name = h[:100].split(b"\0")[0].decode()
        prefix = h[345:500].split(b"\0")[0].decode() if h[257:262] == b"ustar" else ""
        size = int(h[124:136].split(b"\0")[0].strip() or b"0", 8)
        if h[156:157] in (b"0", b"\0"):
            yield (f"{prefix}/{name}" if prefix else name), at + BLOCK, size
        at += BLOCK + -(-size // BLOCK) * BLOCK


def read(stream: SeekableReader, name: str) -> bytes:
    for n, at, size in members(stream):
        if n == name:
            stream.seek(at)
            return stream.read(size)
    raise KeyError(name)
