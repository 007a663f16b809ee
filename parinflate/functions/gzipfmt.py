"""Gzip and zlib containers: headers, footers, members, block-gzip extra fields."""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

MAGIC = b"\x1f\x8b\x08"


class ParinflateError(ValueError):
    """Base of what can be wrong with a compressed file."""


class NotGzip(ParinflateError):
    pass


class Truncated(ParinflateError):
    pass


class CorruptBlock(ParinflateError):
    pass


class ChecksumMismatch(ParinflateError):
    pass


class NonTextByte(ParinflateError):
    pass


@dataclass
class Header:
    start: int
    end: int
    flags: int
    mtime: int
    name: str | None = None
    comment: str | None = None
    extra: dict[str, bytes] = field(default_factory=dict)

    @property
    def block_bytes(self) -> int | None:
        """Compressed size of a block-gzip member."""
        b = self.extra.get("BC")
        return struct.unpack("<H", b)[0] + 1 if b and len(b) == 2 else None


def parse_header(buf: bytes, pos: int = 0) -> Header:
    if buf[pos : pos + 3] != MAGIC:
        raise NotGzip(f"no gzip header at byte {pos}")
    if len(buf) < pos + 10:
        raise Truncated("header")
    flags, mtime = buf[pos + 3], struct.unpack_from("<I", buf, pos + 4)[0]
    if flags & 0xE0:
        raise NotGzip("reserved header flags")
    h, at = Header(pos, 0, flags, mtime), pos + 10
    if flags & 4:
        n = int.from_bytes(buf[at : at + 2], "little")
        field_, at = buf[at + 2 : at + 2 + n], at + 2 + n
        k = 0
        while k + 4 <= len(field_):
            size = int.from_bytes(field_[k + 2 : k + 4], "little")
            h.extra[field_[k : k + 2].decode("latin-1")] = field_[k + 4 : k + 4 + size]
            k += 4 + size
    for bit, attr in ((8, "name"), (16, "comment")):
        if flags & bit:
            stop = buf.find(b"\0", at)
            if stop < 0:
                raise Truncated("header string")
            setattr(h, attr, buf[at:stop].decode("latin-1"))
            at = stop + 1
    if flags & 2:
        if int.from_bytes(buf[at : at + 2], "little") != zlib.crc32(buf[pos:at]) & 0xFFFF:
            raise ChecksumMismatch("header")
        at += 2
    if at > len(buf):
        raise Truncated("header")
    h.end = at
    return h


def parse_footer(buf: bytes, pos: int) -> tuple[int, int]:
    """(crc32, size modulo 2^32)."""
    if pos + 8 > len(buf):
        raise Truncated("footer")
    return struct.unpack_from("<II", buf, pos)


def iter_members(buf: bytes) -> Iterator[tuple[Header, int, bytes, int, int]]:
    """(header, end byte, content, crc32, isize) of each member of a whole file in memory."""
    pos = 0
    while pos < len(buf):
        h = parse_header(buf, pos)
        d = zlib.decompressobj(-15)
        out = d.decompress(buf[h.end :]) + d.flush()
        if not d.eof:
            raise Truncated("member")
        end = len(buf) - len(d.unused_data)
        crc, isize = parse_footer(buf, end)
        if crc != zlib.crc32(out) or isize != len(out) & 0xFFFFFFFF:
            raise ChecksumMismatch(f"member at {pos}")
        yield h, end + 8, out, crc, isize
        pos = end + 8


def decompress(buf: bytes, container: str = "gzip") -> bytes:
    """A whole small file: gzip (all members), zlib or raw."""
    if container == "gzip":
        return b"".join(m[2] for m in iter_members(buf))
    d = zlib.decompressobj(15 if container == "zlib" else -15)
    out = d.decompress(buf) + d.flush()
    if not d.eof:
        raise Truncated(container)
    return out
