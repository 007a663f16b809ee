"""Session helpers: shared folders, intermediate tables and shipping the package to executors."""

from __future__ import annotations

import atexit
import io
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_shipped: set[str] = set()
_written: list[tuple[SparkSession, str]] = []


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once per application, so that workers started anywhere can import it."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    root = Path(__file__).resolve().parent
    buf = io.BytesIO()
    with zipfile.ZipFile(buf, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, f"{root.name}/{p.relative_to(root)}")
    target = Path(tempfile.mkdtemp(prefix="parinflate-ship-")) / "parinflate_pkg.zip"
    target.write_bytes(buf.getvalue())
    spark.sparkContext.addPyFile(str(target))
    _shipped.add(app)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``, or a temporary one where it is unset (tests)."""
    sc = spark.sparkContext
    base = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not base:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = f"file://{tempfile.mkdtemp(prefix='parinflate-shared-')}"
        sc.setCheckpointDir(base)
    return str(base).rstrip("/")


def scratch_path(spark: SparkSession, name: str) -> str:
    """A fresh path in the shared folder; it is removed when the driver's Python ends."""
    path = f"{shared_dir(spark)}/parinflate/{name}-{uuid.uuid4().hex}"
    _written.append((spark, path))
    return path


def delete_path(spark: SparkSession, path: str) -> None:
    """Remove a folder through Hadoop's file system, wherever it is."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


#: Rows of a row group where cells are large: Spark's reader holds up to 4096 rows of one at a time, its writer all of one.
FAT_ROWS = 16


def materialize(df: DataFrame, name: str, compression: str = "zstd", rows: int | None = None) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back: lineage ends here and lost executors cost no recomputation. A row group has ``rows`` at most."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    out = df.write.option("compression", compression)
    (out.option("parquet.block.row.count.limit", rows) if rows else out).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Bytes that a task of heavy work reads, and tasks per core at least where there is enough to do.
TASK_BYTES, WAVES = 256 << 20, 4


def tasks(spark: SparkSession, units: int, n_bytes: int) -> int:
    """How many tasks ``units`` of work over ``n_bytes`` are dealt to: several for each core, none with more than ``TASK_BYTES``, no more than there are units."""
    return max(1, min(units, max(WAVES * spark.sparkContext.defaultParallelism, -(-n_bytes // TASK_BYTES))))


def spread(df: DataFrame, units: int, n_bytes: int) -> DataFrame:
    """``df``, a thin table of units of heavy work, dealt evenly to :func:`tasks`; otherwise the work would run where the thin rows happen to lie, which is one task.

    Rows are dealt in turn, so that neighbours, which tend to be alike, go to different tasks; an explicit count is not merged by AQE.
    """
    n = tasks(df.sparkSession, units, n_bytes)
    return df.repartition(n) if n > 1 else df.coalesce(1)


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


@atexit.register
def _clean() -> None:
    for spark, path in _written:
        try:
            if spark.sparkContext._jsc is not None:
                delete_path(spark, path)
        except Exception:  # the JVM may have gone already
            return


os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
