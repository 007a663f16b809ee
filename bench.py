"""Headline measurements: one JSON line. BENCH_SF_DIR names the tables, BENCH_CPUS the cores; BENCH_FULL adds curves by cores and more formats."""

from __future__ import annotations

import importlib
import json
import os
import subprocess
import sys
import tempfile
import time
from pathlib import Path

ROOT = Path(__file__).resolve().parent
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"
SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", "8"))
FULL = bool(os.environ.get("BENCH_FULL"))


def session(cpus: int = CPUS):
    from pyspark.sql import SparkSession

    tmp = tempfile.mkdtemp(prefix="parinflate-bench-")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", str(cpus)).config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", f"file://{tmp}/shared").config("spark.sql.warehouse.dir", f"{tmp}/warehouse").config("spark.sql.files.maxPartitionBytes", "8m").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def components() -> dict[str, dict[str, float]]:
    """One core: MB/s, mean and deviation over repeats, of finders on random bytes and of other parts."""
    import random
    import zlib

    from parinflate.functions import bits, probe
    from parinflate.operators import finder
    from parinflate.plans import measures

    rng = random.Random(1)
    noise = rng.randbytes(1 << 20)
    text = b" ".join(rng.choice([b"alpha", b"beta", b"gamma", b"delta\n"]) for _ in range(600_000))
    c = zlib.compressobj(6, zlib.DEFLATED, -15)
    z = c.compress(text[: len(text) // 2]) + c.flush(zlib.Z_SYNC_FLUSH)
    cut = 8 * len(z)
    z += c.compress(text[len(text) // 2 :]) + c.flush()
    d = probe.decode_span(z, cut, None, container="raw")
    window = text[: len(text) // 2][-32768:]
    kept = probe.symbols(d.pieces[0]).tobytes()
    out = {}

    def rate(name: str, n: int, f, runs: int = 5) -> None:
        f()
        out[name] = {k: round(v, 4) for k, v in measures.bandwidth(n, measures.timed(f, runs)).items()}

    for v, n, runs in (("zlib", 4 << 10, 2), ("parser", 16 << 10, 2), ("text_only", 1 << 18, 3), ("skip", 1 << 18, 3), ("packed", 1 << 20, 5), ("histset", 1 << 18, 3)):
        part = noise[:n]
        rate(f"finder_{v}", n, lambda part=part, v=v: finder.dynamic(part, variant=v, confirm=0 if v in ("zlib", "parser") else 1024), runs)
    rate("finder_stored", len(noise), lambda: finder.stored(noise, 0, 8 * len(noise)))
    rate("finder_combined", len(noise), lambda: list(finder.candidates(noise)))
    rate("marker_replacement", len(d.pieces[0].data), lambda: probe.apply(d.pieces[0], window))
    rate("marker_replacement_all_symbols", len(kept) // 2, lambda: probe.replaced(kept, window))
    rate("twin_decode", d.out_len, lambda: probe.decode_span(z, cut, None, container="raw"))
    rate("known_window_inflate", d.out_len, lambda: probe.inflate_known(z, cut, None, window, container="raw"))
    rate("newline_count", len(text), lambda: text.count(b"\n"))
    rate("bit_windows", len(noise), lambda: bits.words(noise))
    with tempfile.NamedTemporaryFile() as f:
        rate("write", len(text), lambda: (f.seek(0), f.write(text), f.flush()))
    return out


def curve() -> dict:
    """What a session of ``CPUS`` cores gives for one archive: for the scaling curves, each in a process of its own."""
    from parinflate.operators import index
    from parinflate.plans import baselines, measures, pipeline, workloads

    spark = session()
    arc = workloads.archive(spark, SF, "base64", "pigz_like", copies=int(os.environ.get("BENCH_COPIES", "16")))
    pipeline.decompress(spark, workloads.archive(spark, SF, "base64", "pigz_like"), ordered=False, slot_bytes=1 << 20, verify_crc=False).count()
    t = time.perf_counter()
    idx, _ = index.build(arc, 1 << 21)
    n = baselines.total(index.read(idx))
    first = time.perf_counter() - t
    t = time.perf_counter()
    baselines.total(index.read(idx))
    return {"cpus": CPUS, "first_mb_s": round(n / 1e6 / first, 1), "indexed_mb_s": round(n / 1e6 / (time.perf_counter() - t), 1), "ratio": round(measures.ratio(idx).first().ratio, 3)}


def main() -> None:
    if "--curve" in sys.argv:
        print(json.dumps(curve()))
        return
    from parinflate.operators import index, records
    from parinflate.plans import baselines, measures, pipeline, workloads
    from parinflate.plans.queries import QUERIES

    spark = session()
    took: dict[str, float] = {}
    rates: dict[str, float] = {}

    def run(name: str, f, n_bytes: int = 0):
        t = time.perf_counter()
        out = f()
        took[name] = round(time.perf_counter() - t, 3)
        if n_bytes:
            rates[name] = round(n_bytes / 1e6 / took[name], 1)
        return out

    decompress = lambda arc, slot, **how: baselines.total(pipeline.decompress(spark, arc, slot_bytes=slot, ordered=False, verify_crc=False, **how))
    decompress(workloads.archive(spark, SF, "base64", "pigz_like"), 1 << 20)  # warms the workers
    for name, copies in (("base64", 16), ("documents", 8), ("fastq", 16)):
        arc = workloads.archive(spark, SF, name, "pigz_like", copies=copies)
        slot = 4 << 20 if name == "base64" else 1 << 20
        idx, _ = index.build(arc, slot)
        n = measures.ratio(idx).first().out_len
        run(f"first_{name}", lambda arc=arc, slot=slot: decompress(arc, slot), n)
        run(f"indexed_{name}", lambda idx=idx: baselines.total(index.read(idx)), n)
        run(f"newlines_{name}", lambda idx=idx: records.count_newlines(idx).collect(), n)
        run(f"one_task_{name}", lambda arc=arc: baselines.total(baselines.one_task(arc)), n)
    arc = workloads.archive(spark, SF, "base64", "pigz_like", copies=16)
    for s in (512 << 10, 1 << 20, 2 << 20, 16 << 20, 1 << 40):
        run(f"first_base64_slot_{s >> 10}k", lambda s=s: decompress(arc, s), 16 * 25 * spark.read.parquet(f"{SF}/lineitem.parquet").count())
    sizes = {}
    for layout, level in (("single", 1), ("single", 6), ("single", 9), ("bgzf", 6), ("pigz_like", 1), ("pigz_like", 9), ("stored_only", 0), ("huffman_only", 6)):
        arc = workloads.archive(spark, SF, "documents", layout, level, copies=4)
        idx, _ = index.build(arc, 1 << 20)
        r = measures.ratio(idx).first()
        sizes[f"{layout}-{level}"] = round(r.ratio, 3)
        run(f"matrix_{layout}_{level}", lambda arc=arc: decompress(arc, 1 << 20), r.out_len)
    n = measures.ratio(idx).first().out_len
    for layout, f in (("bgzf", baselines.bgzf), ("zstd_frames", baselines.zstd), ("zstd_frames_unchecked", baselines.zstd), ("zstd_single", baselines.zstd), ("bzip2_streams", baselines.bzip2)):
        arc = workloads.archive(spark, SF, "documents", layout, 6, copies=4)
        run(f"format_{layout}", lambda arc=arc, f=f: baselines.total(f(arc)), n)
    noop = lambda df: df.write.format("noop").mode("overwrite").save()
    for q in ("star_join_over_gz", "index_read_ranges", "filter_cascade_sql", "filter_cascade_engine", "prefetch_adaptive"):
        run(q, lambda q=q: noop(QUERIES[q](spark, SF)))
    # Further queries that __spark_entry__ lists, by name; none where they are not there.
    entry = importlib.import_module("__spark_entry__").queries()
    for q in [x for x in entry if x.split("_")[0] in ("op3", "op4", "op8", "op9", "op10")]:
        run(q, lambda q=q: noop(entry[q](spark, SF)))
    spark.stop()
    parts = components()
    curves = []
    for cpus in (1, 2, 4, 8) if FULL else ():
        done = subprocess.run([sys.executable, __file__, "--curve"], env=os.environ | {"BENCH_CPUS": str(cpus)}, capture_output=True, text=True)
        curves.append(json.loads(done.stdout.strip().splitlines()[-1]))
    base = {k: round(rates[f"first_{k}"] / rates[f"one_task_{k}"], 2) for k in ("base64", "documents", "fastq")}
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "mb_per_s": rates, "speedup_over_one_task": base, "ratio": sizes, "components_mb_per_s_one_core": parts, "curve": curves, "sf": SF.rsplit("sf", 1)[-1], "cpus": CPUS}))


if __name__ == "__main__":
    main()
