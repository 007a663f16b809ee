"""A seekable file object over one compressed file and its index: constant-time seeks, cached chunks, prefetching threads.

Several readers may share a :class:`ChunkStore`: chunks that one of them is having decoded are not decoded again for another.
"""

from __future__ import annotations

import bisect
import io
from collections import OrderedDict
from collections.abc import Callable
from concurrent.futures import Future, ThreadPoolExecutor
from threading import Lock

import pyarrow.dataset as ds
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parinflate.operators.index import GROUP_POINTS, point_bytes
from parinflate.plans.prefetch import STRATEGIES, ChunkCache
from parinflate.sources.io import local

#: Columns of an index but for the windows, which are fetched when a point is decoded.
META = ["file_id", "path", "size", "point_no", "start_bit", "end_bit", "kind", "end_kind", "out_start", "out_len"]


#: Points up to which a reader holds all windows: 64 MiB. Of more points it holds some blocks of neighbours: 32 MiB.
FEW, BLOCKS = 2048, 4


class Windows:
    """Windows of a large index. A window is fetched with its neighbours, as a row group is read for it anyhow; the blocks used last are held."""

    def __init__(self, data: ds.Dataset, file_id: int):
        self.data, self.mine, self.lock = data, ds.field("file_id") == file_id, Lock()
        self.held: OrderedDict[int, dict[int, bytes]] = OrderedDict()
        self.fetched = 0

    def __call__(self, no: int) -> bytes:
        block = no // GROUP_POINTS
        with self.lock:
            if block not in self.held:
                lo, at = block * GROUP_POINTS, ds.field("point_no")
                t = self.data.to_table(columns=["point_no", "window"], filter=self.mine & (at >= lo) & (at < lo + GROUP_POINTS))
                self.held[block] = dict(zip(t["point_no"].to_pylist(), t["window"].to_pylist(), strict=True))
                self.fetched += 1
                if len(self.held) > BLOCKS:
                    self.held.popitem(last=False)
            self.held.move_to_end(block)
            return self.held[block][no]


class Points:
    """The points of one file: positions are held, windows of 32 KiB are fetched where a point is decoded."""

    def __init__(self, rows: list[dict], window: Callable[[int], bytes]):
        rows = sorted(rows, key=lambda r: r["out_start"])
        self.rows = [r for r in rows if r["out_len"]] or rows[:1]
        self.starts = [r["out_start"] for r in self.rows]
        self.size = self.rows[-1]["out_start"] + self.rows[-1]["out_len"] if self.rows else 0
        self.window = window

    @classmethod
    def of(cls, index: DataFrame, file_id: int) -> Points:
        """From an index table; its Parquet files are read where they are local, and through Spark elsewhere."""
        files = [local(f) for f in index.inputFiles()]
        if files and all(files):
            return cls._from(ds.dataset(files), file_id)
        mine = index.where(F.col("file_id") == file_id)
        return cls([r.asDict() for r in mine.select(*META).collect()], lambda no: bytes(mine.where(F.col("point_no") == no).select("window").first()[0]))

    @classmethod
    def load(cls, path: str, file_id: int) -> Points:
        """From a saved index, without Spark: for readers in tasks."""
        return cls._from(ds.dataset(local(path) or path, partitioning=None), file_id)

    @classmethod
    def _from(cls, data: ds.Dataset, file_id: int) -> Points:
        mine = ds.field("file_id") == file_id
        rows = data.to_table(columns=META, filter=mine).to_pylist()
        if len(rows) <= FEW:  # windows of a small index are read at once
            t = data.to_table(columns=["point_no", "window"], filter=mine)
            held = dict(zip(t["point_no"].to_pylist(), t["window"].to_pylist(), strict=True))
            return cls(rows, held.__getitem__)
        return cls(rows, Windows(data, file_id))

    def decode(self, k: int) -> bytes:
        r = self.rows[k]
        return b"".join(point_bytes(r | {"window": self.window(r["point_no"])}))


class ChunkStore:
    """Decodes chunks on threads and knows which are on their way, for all readers that share it."""

    def __init__(self, points: Points, parallel: int = 4):
        self.points, self.parallel = points, parallel
        self.pool, self.lock = ThreadPoolExecutor(parallel), Lock()
        self.in_flight: OrderedDict[int, Future] = OrderedDict()
        self.decoded = self.joined = 0

    def get(self, k: int) -> Future:
        """The chunk, to be waited for; one that is on its way already is joined."""
        with self.lock:
            if k in self.in_flight:
                self.joined += 1
                return self.in_flight[k]
            f = self.in_flight[k] = self.pool.submit(self._decode, k)
        f.add_done_callback(lambda _: self._landed(k))
        return f

    def _decode(self, k: int) -> bytes:
        data = self.points.decode(k)
        with self.lock:
            self.decoded += len(data)
        return data

    def _landed(self, k: int) -> None:
        with self.lock:
            self.in_flight.pop(k, None)

    def close(self) -> None:
        self.pool.shutdown(cancel_futures=True)


class SeekableReader(io.RawIOBase):
    """Reads the decompressed bytes of one file of ``index`` (a table, or :class:`Points`).

    ``seek`` sets the position only; ``read`` finds the points, takes chunks from the caches or decodes them, and plans ahead. A reader
    has its own history and caches; with ``store`` it shares threads and chunks on their way with others.
    """

    def __init__(self, index: DataFrame | Points, file_id: int = 0, parallel: int = 4, strategy: str = "adaptive", access_cache: int = 1, prefetch_cache: int | None = None, store: ChunkStore | None = None):
        points = store.points if store else index if isinstance(index, Points) else Points.of(index, file_id)
        self.points, self.own = points, store is None
        self.store = store or ChunkStore(points, parallel)
        self.size, self.starts = points.size, points.starts
        self.strategy = STRATEGIES[strategy]
        self.cache = ChunkCache(access_cache, prefetch_cache if prefetch_cache is not None else 2 * self.store.parallel)
        self.at, self.history = 0, []
        self.hits = self.misses = 0

    def readable(self) -> bool:
        return True

    def seekable(self) -> bool:
        return True

    def tell(self) -> int:
        return self.at

    def seek(self, offset: int, whence: int = io.SEEK_SET) -> int:
        self.at = max(0, offset + {io.SEEK_SET: 0, io.SEEK_CUR: self.at, io.SEEK_END: self.size}[whence])
        return self.at

    def _chunk(self, k: int) -> bytes:
        if k in self.cache:
            self.hits += 1
            found = self.cache.take(k)
        else:
            self.misses += 1
            found = self.store.get(k)
            self.cache.put(k, found)
        self.history = [*self.history[-64:], k]
        for j in self.strategy(self.history, self.store.parallel, len(self.starts)):
            if j not in self.cache:  # what is cached or on its way is not asked for again
                self.cache.ahead(j, self.store.get(j))
        return found.result()

    def read(self, n: int = -1) -> bytes:
        stop = self.size if n is None or n < 0 else min(self.size, self.at + n)
        out = []
        while self.at < stop:
            k = bisect.bisect_right(self.starts, self.at) - 1
            data, lo = self._chunk(k), self.at - self.starts[k]
            part = data[lo : lo + stop - self.at]
            out.append(part)
            self.at += len(part)
        return b"".join(out)

    def read_many(self, asks: list[tuple[int, int]]) -> list[bytes]:
        """The bytes of every (offset, length), in the order of ``asks``; the position stays.

        They are answered in the order of their offsets, and the chunk before the last one is held for what starts in it: chunks go by in order,
        each decoded once for all that lies in it and asked for ahead like any run.
        """
        if asks and min(asks)[0] < 0:
            raise ValueError("an offset before the file's start")
        out, near = [b""] * len(asks), {}
        for i in sorted(range(len(asks)), key=asks.__getitem__):
            at, stop = asks[i][0], min(self.size, asks[i][0] + asks[i][1])
            parts = []
            while at < stop:
                k = bisect.bisect_right(self.starts, at) - 1
                if k not in near:
                    near = {j: data for j, data in near.items() if j == k - 1} | {k: self._chunk(k)}
                part = near[k][at - self.starts[k] : stop - self.starts[k]]
                parts.append(part)
                at += len(part)
            out[i] = b"".join(parts)
        return out

    def readinto(self, b) -> int:
        data = self.read(len(b))
        b[: len(data)] = data
        return len(data)

    def close(self) -> None:
        if not self.closed and self.own:
            self.store.close()
        super().close()
