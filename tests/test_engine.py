import gzip
import os
import random

import pytest
from pyspark.sql import functions as F

from parinflate.functions import probe
from parinflate.operators import index, rangejoin, records
from parinflate.plans import baselines, pipeline, workloads
from parinflate.sources import io, writers
from parinflate.sources.reader import SeekableReader


@pytest.fixture(scope="module")
def payload():
    random.seed(9)
    return b"".join(random.choice([b"lorem ", b"ipsum ", b"dolor\n", b"sit amet, ", str(random.random()).encode()]) for _ in range(60_000))


@pytest.fixture(scope="module")
def archive(spark, payload, tmp_path_factory):
    p = tmp_path_factory.mktemp("gz") / "a.gz"
    p.write_bytes(gzip.compress(payload, 6, mtime=0))
    return io.from_rows(spark, [(1, str(p))])


def _bytes(out) -> bytes:
    return b"".join(bytes(r.bytes) for r in sorted(out.collect(), key=lambda r: r.out_start))


@pytest.mark.parametrize("how", [{"slot_bytes": 8192}, {"slot_bytes": 60_000, "mode": "serial"}, {"slot_bytes": 1 << 30}, {"slot_bytes": 30_000, "materialize_as": "symbols", "group": 2}])
def test_output_is_the_same_for_all_ways(spark, archive, payload, how):
    assert _bytes(pipeline.decompress(spark, archive, verify_crc=True, **how)) == payload


def test_index_reads_seeks_and_ranges(spark, archive, payload, tmp_path):
    idx, counters = index.build(archive, 20_000, group=3)
    assert counters["spans"] > 3 and idx.agg(F.sum("out_len")).first()[0] == len(payload)
    index.save(idx, f"file://{tmp_path}/idx")
    idx = index.load(spark, f"file://{tmp_path}/idx")
    wide = index.respace(idx, 200_000)
    assert wide.count() < idx.count() and _bytes(index.read(wide)) == payload
    asks = [(1, k, o, n) for k, (o, n) in enumerate([(0, 10), (len(payload) - 5, 5), (70_000, 150_000), (123, 1)])]
    got = {r.request_id: bytes(r.bytes) for r in index.read_ranges(spark.createDataFrame(asks, "file_id long, request_id long, offset long, len long"), idx, 50_000).collect()}
    assert got == {k: payload[o : o + n] for _, k, o, n in asks}
    with SeekableReader(idx, 1, parallel=2) as r:
        for _, _, o, n in asks:
            assert r.seek(o) == o and r.read(n) == payload[o : o + n]
        r.seek(-7, os.SEEK_END)
        assert r.read() == payload[-7:]
    lines = [r.line for r in records.lines(idx, numbered=True).orderBy("line_no").collect()]
    assert lines == payload.decode().split("\n")[: len(lines)] and len(lines) >= payload.count(b"\n")


def test_small_empty_and_damaged_files(spark, tmp_path):
    rows = []
    for k, data in enumerate([b"", b"x", b"line\n" * 3]):
        (tmp_path / f"{k}.gz").write_bytes(gzip.compress(data, mtime=0))
        rows.append((k, str(tmp_path / f"{k}.gz")))
    out = pipeline.decompress(spark, io.from_rows(spark, rows), slot_bytes=8192)
    assert {r.file_id: bytes(r.bytes) for r in out.collect()} == {0: b"", 1: b"x", 2: b"line\n" * 3}
    bad = tmp_path / "bad.gz"
    bad.write_bytes(gzip.compress(b"abc" * 1000, mtime=0)[:-6])
    with pytest.raises(Exception, match="trunc|footer"):
        pipeline.decompress(spark, io.from_rows(spark, [(9, str(bad))]))


@pytest.mark.parametrize("step", [64, 1 << 16])
def test_no_stored_block_is_seen_inside_another_block(monkeypatch, step):
    """The tail that closes a span before a stored block can end the block it falls into; the span was taken for linked and the file for broken."""
    monkeypatch.setattr(probe, "TWIN_STEP", step)
    data = bytes(range(256)) * 10
    # All codes but two have eight bits, and the end's code is all ones; a block that is not the last.
    z = bytearray(writers.single_dynamic_block(data)[10:-8])
    z[0] &= 0xFE
    end = next(k for k in range(8 * len(z) - 8, 8 * len(z) + 1) if probe.decode_span(bytes(z), 0, k, container="raw").ok)
    buf = bytes(z) + bytes(end % 8 > 5) + b"\x02\0\xfd\xffok" + b"\x03\0"
    last = len(buf) - 8
    said = [k for k in range(200, last + 4) if probe.decode_span(buf, 0, 8 * k - 3, end_kind="stored", container="raw").ok]
    assert said == [last]


@pytest.mark.parametrize("step", [1, 7, 4000])
def test_lines_of_cells_wherever_they_are_cut(spark, step):
    """lines come from cells without their file being one row."""
    files = {1: "a\n\nbé\n" + "c" * 50 + "\nend", 2: "x" * 60 + "\n", 3: "\n", 4: "no newline"}
    rows = [(i, at, bytearray(t.encode()[at : at + step])) for i, t in files.items() for at in range(0, len(t.encode()), step)]
    random.Random(step).shuffle(rows)
    got = records.cell_lines(spark.createDataFrame(rows, "file_id long, seq long, bytes binary"))
    want = sorted((i, x) for i, t in files.items() for x in (t[:-1] if t.endswith("\n") else t).split("\n"))
    assert sorted((r.file_id, r.line) for r in got.collect()) == want


@pytest.mark.parametrize("layout", ["single_dynamic_block", "nested"])
def test_writers_of_one_block_and_of_nested_files_hold_no_file(tmp_path, layout):
    """F1, F2."""
    import tracemalloc
    import zlib

    piece = b"".join(b"%d,%d\n" % (k, k * k % 977) for k in range(30_000))[: 1 << 18]
    n = 48
    tracemalloc.start()
    f = writers._File(str(tmp_path / "a.gz"), layout, 6)
    for _ in range(n):
        f.add(piece, len(piece), zlib.crc32(piece))
    f.close()
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    got = gzip.decompress((tmp_path / "a.gz").read_bytes())
    assert (gzip.decompress(got) if layout == "nested" else got) == piece * n
    assert peak < (64 << 20 if layout == "single_dynamic_block" else 8 << 20)


def test_bzip2_blocks_at_all_shifts_and_across_slots(spark, payload, tmp_path):
    """a slot reads on only as far as its last block goes."""
    import bz2

    for r in range(8):
        wide = (baselines.BZIP2_BLOCK << 16 + r | 5).to_bytes(9, "big")
        assert baselines.bzip2_magic(b"BZh9" + wide, baselines.BZIP2_BLOCK) == [8 * 4 + 72 - 64 - r]
    p = tmp_path / "a.bz2"
    p.write_bytes(bz2.compress(payload, 1) + bz2.compress(payload[:5000], 1))
    out = baselines.bzip2(io.from_rows(spark, [(1, str(p))]), slot_bytes=9000, look=1000).collect()
    assert b"".join(bytes(r.bytes) for r in sorted(out, key=lambda r: r.seq)) == payload + payload[:5000]


def test_slices_by_value(spark):
    """lines of each file are compressed in slices, not one by one."""
    rows = [(f"f{k % 3}", k, f"line {k}") for k in range(999)]
    got = writers.slices_by(spark.createDataFrame(rows, "path string, k int, line string"), "path", ["k"], slice_bytes=500).collect()
    assert len(got) < 60
    for f in range(3):
        mine = sorted((r for r in got if r.path == f"f{f}"), key=lambda r: r.part)
        assert b"".join(bytes(r.data) for r in mine).decode() == "".join(f"line {k}\n" for k in range(f, 999, 3))


@pytest.mark.parametrize("name", ["valid_precode_histograms", "kraft_examples", "amdahl_bound", "seek_cost_bound"])
def test_cost_models_and_codes_read_given_tables(spark, sf, name):
    """F25, F28, F29, F30."""
    import duckdb

    from parinflate.plans import oracles, queries

    got = queries.QUERIES[name](spark, sf)
    assert any(f.endswith(("orders.parquet", "documents.parquet")) for f in got.inputFiles())
    con = duckdb.connect()
    for t in ("orders", "documents"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    assert sorted(tuple(r) for r in got.collect()) == sorted(con.sql(oracles.ORACLES[name]).fetchall())


@pytest.mark.parametrize("mode", ["complete", "append"])
def test_stream_results_are_files_of_executors(spark, tmp_path, mode):
    """results of a stream, over several batches, do not pass through a sink in the driver's memory."""
    from parinflate.streaming import stream

    spark.createDataFrame([(k, k % 3) for k in range(30)], "id int, g int").repartition(3).write.parquet(str(tmp_path / "in"))
    s = spark.readStream.schema("id int, g int").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    got = stream.run(s.groupBy("g").count() if mode == "complete" else s, mode, f"t_{mode}")
    assert got.inputFiles() and not spark.catalog.tableExists(f"t_{mode}")
    assert sorted(tuple(r) for r in got.collect()) == ([(0, 10), (1, 10), (2, 10)] if mode == "complete" else [(k, k % 3) for k in range(30)])
    (tmp_path / "none").mkdir()
    assert stream.run(spark.readStream.schema("id int").parquet(str(tmp_path / "none")), "append", "t_none").count() == 0


def test_finder_variants_share_their_rows(spark, sf):
    """the random rows are made and sorted once for the three variants."""
    from parinflate.plans import queries

    got = queries.QUERIES["finder_variants_agree"](spark, sf)
    assert got._jdf.queryExecution().optimizedPlan().toString().count("MapInArrow") == 1
    assert {(r["values"], r.variants) for r in got.collect()} == {(1, 3)}


def test_finder_variants_move_keys_alone(spark, sf):
    """keys are dealt and sorted, not a row of bytes per salt; the bytes of a salt are tested in one piece per task."""
    from parinflate.plans import queries, workloads

    plan = queries.QUERIES["finder_variants_agree"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate" not in plan
    counts = {}
    for r in queries._cascades(spark, sf, "packed", "skip").where("step <> 'passed'").groupBy("salt", "variant").agg(F.sum("n").alias("n")).collect():
        counts[r.salt, r.variant] = r.n
    n = spark.read.parquet(f"{sf}/lineitem.parquet").count()
    assert n < queries._CASCADE_LEAST and counts == {(k, v): 8 * (16 * n - 400) for k in range(workloads.SALTS) for v in ("packed", "skip")}


def test_cascades_test_every_offset_once(spark, sf, monkeypatch):
    """bytes are carried over from one piece of a task to the next."""
    from parinflate.plans import queries

    of = lambda: {(r.salt, r.step): r.n for r in queries._cascades(spark, sf, "packed").collect()}
    whole = of()
    monkeypatch.setattr(queries, "_CASCADE_ROWS", 100)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "333")
    try:
        assert of() == whole
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_baselines_agree(spark, archive, payload):
    assert baselines.total(baselines.one_task(archive)) == baselines.total(baselines.helper_threads(archive)) == len(payload)
    assert _bytes(index.read(baselines.serial_index(archive, 20_000))) == payload


def test_range_joins(spark):
    a = spark.createDataFrame([(1, 5), (1, 12), (1, 0)], "k int, t int")
    b = spark.createDataFrame([(1, 3, "x"), (1, 10, "y")], "k int, u int, v string")
    got = {(r.t, r.v) for r in rangejoin.asof(a, b, "k", "t", "u", ["v"]).collect()}
    assert got == {(5, "x"), (12, "y"), (0, None)}
    p = spark.createDataFrame([(1, 0, 25), (1, 30, 31)], "k int, a int, b int")
    q = spark.createDataFrame([(1, 10, 20), (1, 24, 40)], "k int, c int, d int")
    pairs = sorted((r.a, r.c) for r in rangejoin.overlap(p, q, "k", ("a", "b"), ("c", "d"), 8).collect())
    assert pairs == [(0, 10), (0, 24), (30, 24)]


def test_layouts_round_trip(spark, sf):
    want = spark.read.parquet(f"{sf}/nation.parquet").count()
    for layout in ("multi_member", "bgzf"):
        idx, _ = workloads.indexed(spark, sf, "nation", layout)
        assert records.json_table(idx, workloads.SCHEMA["nation"]).count() == want


def test_entry_points():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())


def test_heavy_work_is_dealt_to_many_tasks(spark, archive):
    from parinflate.operators import spans
    from parinflate.runtime import WAVES, materialize, tasks

    cores = spark.sparkContext.defaultParallelism
    assert tasks(spark, 10**6, 10**9) == WAVES * cores and tasks(spark, 3, 10**15) == 3 and tasks(spark, 10**8, 1 << 50) == (1 << 50) // (256 << 20) and tasks(spark, 0, 0) == 1
    slots = materialize(spans.plan(archive, 4096), "slots")
    n = min(slots.count(), WAVES * cores)
    parts = lambda df: df.select(F.spark_partition_id().alias("p")).distinct().count()
    found = spans.find(slots)
    assert found.rdd.getNumPartitions() == n and parts(spans._spread(slots)) == n
    todo = spans.hints(slots, materialize(found, "found"))
    assert spans.decode(todo).rdd.getNumPartitions() == min(todo.count(), WAVES * cores)
    idx, _ = index.build(archive, 4096)
    assert index.read(idx).rdd.getNumPartitions() == min(idx.count(), WAVES * cores)


def test_readers_share_what_is_on_its_way(spark, archive, payload):
    from concurrent.futures import ThreadPoolExecutor

    from parinflate.sources.reader import ChunkStore, Points

    idx, _ = index.build(archive, 20_000)
    points = Points.of(idx, 1)
    asked, decode = [], points.decode
    points.decode = lambda k: asked.append(k) or decode(k)
    store = ChunkStore(points, 4)
    readers = [SeekableReader(points, store=store, strategy="none") for _ in range(6)]

    def one(r):
        r.seek(100)
        return r.read(50)

    with ThreadPoolExecutor(6) as pool:
        assert set(pool.map(one, readers)) == {payload[100:150]}
    assert len(asked) + store.joined == 6
    whole = [SeekableReader(points, store=store) for _ in range(2)]
    assert all(r.read() == payload for r in whole)
    store.close()


def test_many_requests_of_a_reader_decode_each_chunk_once(spark, archive, payload, tmp_path, monkeypatch):
    """each request decoded its chunk anew, and of a large index each chunk read a row group for its one window."""
    from parinflate.sources import reader

    monkeypatch.setattr(reader, "FEW", 0)
    monkeypatch.setattr(reader, "GROUP_POINTS", 2)
    monkeypatch.setattr(reader, "BLOCKS", 1)
    idx, _ = index.build(archive, 8192)
    index.save(idx, f"file://{tmp_path}/idx")
    points = reader.Points.load(f"file://{tmp_path}/idx", 1)
    assert len(points.starts) > 4
    asks = [(k * 7919 % len(payload), k % 90) for k in range(3000)] + [(s - 3, 6) for s in points.starts[1:]] + [(0, len(payload) + 9), (len(payload), 5), (len(payload) + 7, 1)]
    with SeekableReader(points, parallel=1) as r:
        assert r.read_many(asks[:-3]) == [payload[o : o + n] for o, n in asks[:-3]]
        assert r.store.decoded == len(payload) and points.window.fetched == -(-len(points.starts) // 2)
        assert r.read_many(asks) == [payload[o : o + n] for o, n in asks] and r.read_many([]) == [] and r.tell() == 0
        with pytest.raises(ValueError):
            r.read_many([(-1, 2)])


def test_adaptive_replay_of_batches_equals_one(spark, sf):
    """The strategy against a restatement that keeps everything it ever saw, in one batch and over micro-batches with state."""
    import __spark_entry__ as e

    def by_hand(trace, degree, chunks):
        access, ahead, hits = [], [], 0
        for t, c in enumerate(trace):
            if c in access or c in ahead:
                hits += 1
                ahead = [x for x in ahead if x != c]
            access = [c]
            recent = trace[max(0, t + 1 - 2 * degree) : t + 1]
            want, told = [], set()
            if t == 0:
                want = [x for x in range(c + 1, c + 1 + degree) if x < chunks]
            for end in range(len(recent) - 1, -1, -1) if t else []:
                if recent[end] in told:
                    continue
                run, nxt = [recent[end]], recent[end] - 1
                for k in range(end - 1, -1, -1):
                    if recent[k] == nxt:
                        run.append(nxt)
                        nxt -= 1
                told |= set(run)
                if len(run) > 1:
                    want += [x for x in range(recent[end] + 1, recent[end] + 1 + min(degree, 2 ** (len(run) - 1))) if x < chunks and x not in want][: degree - len(want)]
            for x in want:
                if x not in access:
                    ahead = [*(y for y in ahead if y != x), x][-2 * degree :]
        return hits

    from parinflate.plans import prefetch

    rows = workloads.trace(spark, sf).collect()
    traces = {}
    for r in sorted(rows, key=lambda r: r.seq):
        traces.setdefault(r.reader_id, []).append(r.point_no)
    got = {r.reader_id: r.hits for r in prefetch.replay(workloads.trace(spark, sf), "adaptive", degree=4, chunks=8).collect()}
    assert got == {k: by_hand(t, 4, 8) for k, t in traces.items()}
    # One stream: a run at the very end of the trace earns exponentially, without limit to how far back it goes.
    def one_stream(trace, degree, chunks):
        access, ahead, hits = [], [], 0
        for t, c in enumerate(trace):
            hits += c in access or c in ahead
            ahead = [x for x in ahead if x != c]
            access, r = [c], 1
            while r <= t and trace[t - r] == trace[t - r + 1] - 1:
                r += 1
            for x in range(c + 1, c + 1 + (degree if t == 0 else min(degree, 2 ** (r - 1)) if r > 1 else 0)):
                if x < chunks:
                    ahead = [*(y for y in ahead if y != x), x][-2 * degree :]
        return hits

    got = {r.reader_id: r.hits for r in e.queries()["prefetch_single_stream"](spark, sf).collect()}
    assert got == {k: one_stream(t, 4, 8) for k, t in traces.items()}
    streamed = {r.reader_id: (r.hits, r.misses) for r in e.queries()["stream_replay_adaptive"](spark, sf).collect()}
    want = {r.reader_id: (r.hits, r.misses) for r in prefetch.replay(workloads.trace(spark, sf), "adaptive").collect()}
    assert streamed == want


def test_cascade_shares_are_the_published_ones(spark):
    from parinflate.plans.queries import QUERIES

    rows = {r.step: r for r in QUERIES["filter_cascade_table"](spark, "/root/testdata/sf0.01").collect()}
    assert len(rows) == 11 and all(abs(r.z) < 6 for s, r in rows.items() if r.published * r.bits > 5), {s: r.z for s, r in rows.items()}
    assert abs(sum(r.mean for r in rows.values()) - 1) < 1e-9


def test_source_prunes_row_groups_and_writes(spark, payload, tmp_path):
    from parinflate.sources.gzip_source import ParinflateSource, _Plain

    payload = b"".join(payload[k * 997 :] for k in range(6))
    (tmp_path / "big.gz").write_bytes(gzip.compress(payload, 6, mtime=0))
    idx, _ = index.build(io.from_rows(spark, [(1, str(tmp_path / "big.gz"))]), 16384)
    assert idx.count() > 8
    old, index.GROUP_POINTS = index.GROUP_POINTS, 2
    index.save(idx, f"file://{tmp_path}/idx")
    index.GROUP_POINTS = old
    reader = _Plain({"index": f"{tmp_path}/idx"}, None)
    every = len(reader.partitions())
    reader.limits = [("out_start", "<", len(payload) // 8)]
    few = reader.partitions()
    assert every > 4 and 0 < len(few) < every / 2
    spark.dataSource.register(ParinflateSource)
    lines = spark.read.format("parinflate").option("format", "lines").option("index", f"{tmp_path}/idx").load()
    got = sorted((r.out_pos, r.line) for r in lines.collect())
    want, at = [], 0
    for x in payload.decode().split("\n"):
        want.append((at, x))
        at += len(x) + 1
    assert got == [w for w in want if w[1] or w[0] < len(payload)]
    df = spark.createDataFrame([("a",), ("b",), ("é",)], "line string")
    for layout in ("single", "bgzf", "multi_member"):
        df.write.format("parinflate").option("layout", layout).mode("overwrite").save(f"{tmp_path}/out")
        back = spark.read.format("parinflate").option("format", "lines").load(f"{tmp_path}/out")
        assert sorted(r.line for r in back.collect()) == ["a", "b", "é"]
    with pytest.raises(Exception, match="one column"):
        spark.range(3).selectExpr("id", "id AS x").write.format("parinflate").mode("append").save(f"{tmp_path}/no")


def test_damage_is_said_and_recovered(spark, payload, tmp_path):
    z = bytearray(gzip.compress(payload, 6, mtime=0))
    cut = len(z) // 2
    subtle = bytearray(z)
    subtle[-6] ^= 1
    z[cut : cut + 3000] = random.Random(3).randbytes(3000)
    for name, data in (("bad", z), ("good", gzip.compress(payload[:5000], mtime=0)), ("sum", subtle)):
        (tmp_path / f"{name}.gz").write_bytes(data)
    every = io.from_rows(spark, [(k, str(tmp_path / f"{n}.gz")) for k, n in ((1, "bad"), (2, "good"), (3, "sum"))])
    assert {r.status for r in pipeline.decompress(spark, every.where("file_id = 3"), slot_bytes=8192, on_error="skip").collect()} == {"bad_checksum"}
    with pytest.raises(Exception, match="member 0"):
        pipeline.decompress(spark, every.where("file_id = 3"), slot_bytes=8192)
    arc = every.where("file_id < 3")
    out = pipeline.decompress(spark, arc, slot_bytes=8192, on_error="skip").collect()
    assert {(r.file_id, r.status) for r in out} == {(1, "cut"), (2, "complete")}
    front = b"".join(bytes(r.bytes) for r in out if r.file_id == 1)
    assert payload.startswith(front) and len(front) > len(payload) // 4
    got = pipeline.decompress(spark, arc, slot_bytes=8192, on_error="recover", ordered=False)
    kinds = {r.status for r in got.collect()}
    assert kinds == {"sound", "partial", "damaged"}
    n = sum(len(r.bytes) for r in got.collect() if r.file_id == 1 and r.status != "damaged")
    assert n > 0.7 * len(payload)


def test_layouts_of_other_formats_come_back(spark, sf):
    want = spark.read.parquet(f"{sf}/nation.parquet").count()
    for layout in ("zstd_single", "zstd_single_unchecked", "zstd_frames_unchecked"):
        assert baselines.total(baselines.zstd(workloads.archive(spark, sf, "documents", layout), 1 << 16)) == baselines.total(baselines.one_task(workloads.archive(spark, sf, "documents", "single")))
    assert want == 25


def test_row_groups_of_large_cells_are_small(spark, tmp_path, monkeypatch):
    """A reader holds up to 4096 rows of a row group, a gigabyte of slices; executors ended for memory."""
    import pyarrow.parquet as pq

    kept, made = [], writers.materialize
    monkeypatch.setattr(writers, "materialize", lambda *a: kept.append(made(*a)) or kept[-1])
    lines = spark.range(400).select("id", F.repeat(F.lit("x"), 99).alias("line"))
    assert writers.write(writers.slices(lines, ["id"], parts=2, slice_bytes=100), f"{tmp_path}/a.gz", "pigz_like") == 40_000
    assert gzip.decompress((tmp_path / "a.gz").read_bytes()) == (b"x" * 99 + b"\n") * 400
    groups = [m.row_group(k).num_rows for f in kept[0].inputFiles() for m in [pq.ParquetFile(io.local(f)).metadata] for k in range(m.num_row_groups)]
    assert sum(groups) == 400 and max(groups) <= 16
