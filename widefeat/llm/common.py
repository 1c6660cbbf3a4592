"""What all operators of this package share: tables, staged files, held-out rows, text slices."""

from __future__ import annotations

import atexit
import ctypes
import os
import shutil
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from pathlib import Path

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SLICE_CHARS = 2_000_000
ARROW_BYTES, BATCH_BYTES = 4 << 20, "spark.sql.execution.arrow.maxBytesPerBatch"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The table `name`; only Spark's reader opens the path."""
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def ship(spark: SparkSession) -> None:
    """Send this package's source to the executors once per application, and texts to their workers some ARROW_BYTES at a time.

    A batch is held by the JVM and by the worker, in buffers of up to twice its size, so it is bounded by bytes, not by rows.
    """
    spark.conf.set(BATCH_BYTES, str(ARROW_BYTES))
    sc = spark.sparkContext
    if getattr(sc, "_widefeat_shipped", False):
        return
    root = Path(__file__).resolve().parents[1]
    folder = Path(tempfile.mkdtemp(prefix="widefeat-src-"))
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    with zipfile.ZipFile(folder / "widefeat_src.zip", "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, f"{root.name}/{p.relative_to(root)}")
    sc.addPyFile(str(folder / "widefeat_src.zip"))
    sc._widefeat_shipped = True


def shared_base(spark: SparkSession) -> str:
    """The folder that driver and executors share: `spark.checkpoint.dir` of the session.

    Where it is unset, as in tests, a temporary folder is set, in local mode only.
    """
    sc = spark.sparkContext
    base = sc.getConf().get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not base:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="widefeat-shared-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        sc.setCheckpointDir(f"file://{folder}")
        base = f"file://{folder}"
    return base.rstrip("/")


def file_system(spark: SparkSession, path: str):
    """Hadoop's file system and path object of `path`, whatever its scheme."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), at


def staging_path(spark: SparkSession, name: str) -> str:
    """A new path below this application's folder, which goes when the application ends."""
    sc = spark.sparkContext
    folder = f"{shared_base(spark)}/widefeat-{sc.applicationId}"
    if not getattr(sc, "_widefeat_staging", False):
        fs, at = file_system(spark, folder)
        fs.deleteOnExit(at)
        sc._widefeat_staging = True
    return f"{folder}/{name}-{uuid.uuid4().hex[:12]}"


def staged(df: DataFrame, name: str, **options: str) -> DataFrame:
    """Write `df` to the shared folder and read it again: cuts the lineage, survives lost executors."""
    spark = df.sparkSession
    path = staging_path(spark, name)
    writer = df.write
    for k, v in ({"compression": "zstd"} | options).items():
        writer = writer.option(k, v)
    writer.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.staged_path = path
    return out


def discard(*frames: DataFrame) -> None:
    """Delete staged tables that nothing reads any more."""
    for df in frames:
        fs, at = file_system(df.sparkSession, df.staged_path)
        fs.delete(at, True)


def unused(df: DataFrame, name: str) -> str:
    """`name`, with underscores in front until no column of `df` has it."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = "_" + name
    return name


HEAVY = 1000


def heavy_keys(rows: DataFrame, keys: list[str]) -> DataFrame | None:
    """Keys that hold more than one in HEAVY of the rows; there are fewer than HEAVY of them, whatever the data."""
    counts = rows.groupBy(*keys).agg(F.count("*").alias("_n"))
    total = rows.count()
    found = counts.where(F.col("_n") * HEAVY > total).where("_n > 1").drop("_n").collect()
    return rows.sparkSession.createDataFrame(found, counts.drop("_n").schema) if found else None


def spread_join(rows: DataFrame, table: DataFrame, keys: str | list[str], how: str = "inner", heavy: DataFrame | bool | None = None) -> DataFrame:
    """`rows` joined with `table`, which has at most one row a key, so that no task gets more than its part of the rows.

    Rows of heavy keys stay where they are and meet a broadcast of fewer than HEAVY rows of `table`; the rest is shuffled.
    Both are read twice, so they should be staged. `heavy`: these keys if they are known, False if there are none.
    """
    keys = [keys] if isinstance(keys, str) else keys
    heavy = (heavy_keys(rows, keys) or False) if heavy is None else heavy
    if heavy is False:
        return rows.join(table, keys, how)
    few = F.broadcast(table.join(F.broadcast(heavy), keys, "left_semi"))
    light = rows.join(F.broadcast(heavy), keys, "left_anti").join(table, keys, how)
    return light.unionByName(rows.join(F.broadcast(heavy), keys, "left_semi").join(few, keys, how))


def held_out(doc_id: Column | str) -> Column:
    """True for rows that no model of this package learns from: crc32 of the id as text, modulo 3, is 1."""
    c = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.coalesce(F.crc32(c.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def text_slices(batch: pa.RecordBatch, column: str = "text", most: int = SLICE_CHARS) -> Iterator[pa.RecordBatch]:
    """Parts of a batch of some `most` bytes of text each (one row at least), so memory doesn't follow the batch's size.

    What the parts before have left unused goes back to the system: a worker lives on, and other tasks follow.
    """
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_pylist()
    start = total = 0
    for i, n in enumerate(sizes):
        if total and total + n > most:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += n
    if start < len(sizes):
        yield batch.slice(start)
    give_back()


def give_back() -> None:
    """Return this process's unused memory, Arrow's and the C library's, to the system."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):  # glibc only
        trim(0)


def local_scratch() -> str:
    """A folder of this process's machine for memory-mapped copies of broadcast models (never data)."""
    return os.environ.get("TMPDIR") or tempfile.gettempdir()
