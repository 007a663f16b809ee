"""Bounded tables that Python workers keep between tasks, and thin tables that may be broadcast."""

from __future__ import annotations

import ctypes
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows of a thin table (tens of bytes a row) up to which it is broadcast.
FEW_ROWS = 100_000

_owner: str | None = None
_clear: dict[str, Callable[[], None]] = {}


def claim(owner: str, clear: Callable[[], None]) -> None:
    """Called as a task of ``owner`` starts: tables of the operator that ran before it in this worker are emptied and their memory goes back to the system."""
    global _owner
    _clear[owner] = clear
    if _owner != owner:
        if _owner is not None:
            _clear[_owner]()
        _owner = owner
    release()


def release() -> None:
    """Free memory that this worker holds but does not use."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        return


def few(df: DataFrame, rows: int = FEW_ROWS) -> DataFrame:
    """``df``, thin and already written, with a broadcast hint where it has at most ``rows`` rows; a longer one joins by shuffle, where AQE splits hot keys."""
    return F.broadcast(df) if df.count() <= rows else df


class Bounded(dict):
    """What ``make`` gives for a key, kept in about ``most`` bytes by ``weigh``.

    There are two generations: when the younger weighs half of ``most`` it becomes the older, whose keys come back when they are met
    again and are dropped with the next change. So what is met often stays.
    """

    def __init__(self, make: Callable, weigh: Callable[[object, object], int], most: int):
        self.make, self.weigh, self.most, self.held, self.old = make, weigh, most, 0, {}

    def clear(self) -> None:
        super().clear()
        self.held, self.old = 0, {}

    def __missing__(self, key):
        v = self.old.get(key)
        if v is None:
            v = self.make(key)
        n = self.weigh(key, v)
        if n > self.most >> 6:
            return v
        if 2 * (self.held + n) > self.most:
            self.old = dict(self)
            super().clear()
            self.held = 0
        self.held += n
        self[key] = v
        return v
