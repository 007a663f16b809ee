"""What to decode next: strategies over the history of chunk numbers, a cache with a separate prefetch cache, and replay of traces."""

from __future__ import annotations

from collections import OrderedDict
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame

Strategy = Callable[[list[int], int, int], list[int]]


def none(history: list[int], degree: int, chunks: int) -> list[int]:
    return []


def fixed(history: list[int], degree: int, chunks: int) -> list[int]:
    """The next ``degree`` chunks."""
    return [c for c in range(history[-1] + 1, history[-1] + 1 + degree) if c < chunks]


def _run(history: list[int], end: int) -> int:
    """Length of the run of consecutive chunks that ends at place ``end``, other accesses between them allowed."""
    n, want = 1, history[end] - 1
    for k in range(end - 1, -1, -1):
        if history[k] == want:
            n, want = n + 1, want - 1
    return n


def single(history: list[int], degree: int, chunks: int) -> list[int]:
    """One stream: a run of length r at the last access earns 2^(r-1) chunks."""
    r = 1
    while r < len(history) and history[-r - 1] == history[-r] - 1:
        r += 1
    n = degree if len(history) == 1 else min(degree, 1 << (r - 1)) if r > 1 else 0
    return [c for c in range(history[-1] + 1, history[-1] + 1 + n) if c < chunks]


def adaptive(history: list[int], degree: int, chunks: int) -> list[int]:
    """Several interleaved streams: each run in the last 2 * degree accesses earns exponentially with its length, newest first, up to ``degree`` in all; the very first access earns it all."""
    if len(history) == 1:
        return fixed(history, degree, chunks)
    recent, out, ends = history[-2 * degree :], [], set()
    for end in range(len(recent) - 1, -1, -1):
        if recent[end] in ends:
            continue
        r = _run(recent, end)
        ends.update(range(recent[end] - r + 1, recent[end] + 1))
        if r < 2:
            continue
        for c in range(recent[end] + 1, recent[end] + 1 + min(degree, 1 << (r - 1))):
            if c < chunks and c not in out and len(out) < degree:
                out.append(c)
    return out


STRATEGIES: dict[str, Strategy] = {"none": none, "fixed": fixed, "single": single, "adaptive": adaptive}


class ChunkCache:
    """An access cache and a prefetch cache that do not evict one another; both drop what was used longest ago."""

    def __init__(self, access: int, prefetch: int):
        self.access_size, self.prefetch_size = access, prefetch
        self.access: OrderedDict[int, object] = OrderedDict()
        self.prefetch: OrderedDict[int, object] = OrderedDict()
        self.unused = self.evictions = 0

    def __contains__(self, c: int) -> bool:
        return c in self.access or c in self.prefetch

    def take(self, c: int):
        """A cached chunk, moved to the access cache."""
        v = self.access.pop(c) if c in self.access else self.prefetch.pop(c)
        self.put(c, v)
        return v

    def put(self, c: int, v) -> None:
        self.access[c] = v
        while len(self.access) > self.access_size:
            self.access.popitem(last=False)
            self.evictions += 1

    def ahead(self, c: int, v) -> None:
        self.prefetch[c] = v
        self.prefetch.move_to_end(c)
        while len(self.prefetch) > self.prefetch_size:
            self.prefetch.popitem(last=False)
            self.unused += 1


def replay_one(trace: list[int], strategy: str = "adaptive", degree: int = 4, chunks: int = 1 << 30, access: int = 1, prefetch: int | None = None, delay: int = 0, history: list[int] | None = None, cache: ChunkCache | None = None) -> dict[str, int]:
    """Counters of one reader's trace. A chunk asked for ahead is ready ``delay`` accesses later; a hit before that is late."""
    cache = cache or ChunkCache(access, prefetch if prefetch is not None else 2 * degree)
    history = history if history is not None else []
    hits = late = misses = asked = 0
    for t, c in enumerate(trace):
        if c in cache:
            ready = cache.take(c)
            hits += 1
            late += isinstance(ready, int) and ready > t
        else:
            misses += 1
            cache.put(c, t)
        history.append(c)
        # Prefetching follows every access, hit or not; what is cached is only made recent.
        for k in STRATEGIES[strategy](history, degree, chunks):
            if k in cache.access:
                continue
            asked += k not in cache.prefetch
            cache.ahead(k, cache.prefetch.get(k, t + delay))
    return {"accesses": len(trace), "hits": hits, "late_hits": late, "misses": misses, "prefetched": asked, "unused": cache.unused + len(cache.prefetch), "evictions": cache.evictions}


REPLAY = "reader_id long, accesses long, hits long, late_hits long, misses long, prefetched long, unused long, evictions long"


def replay(trace: DataFrame, strategy: str = "adaptive", degree: int = 4, chunks: int = 1 << 30, access: int = 1, prefetch: int | None = None, delay: int = 0) -> DataFrame:
    """Counters per reader of a table (reader_id, seq, point_no)."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("seq")
        return pd.DataFrame([{"reader_id": int(pdf["reader_id"].iloc[0]), **replay_one(pdf["point_no"].tolist(), strategy, degree, chunks, access, prefetch, delay)}])

    return trace.select("reader_id", "seq", "point_no").groupBy("reader_id").applyInPandas(run, REPLAY)
