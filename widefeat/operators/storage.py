"""Files of physical tables: staged writes, sizes, deletion; only through Hadoop's file systems."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
import zipfile
from collections.abc import Sequence
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..catalog import logical_name, stored_name
from ..model import BATCH, KEYS, Physical


def ship(spark: SparkSession) -> None:
    """Send the package's source to the executors, once per application: Python lanes import it there."""
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
    """spark.checkpoint.dir of the session, or in local mode a temporary folder."""
    sc = spark.sparkContext
    base = sc.getConf().get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not base:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="widefeat-warehouse-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        sc.setCheckpointDir(f"file://{folder}")
        base = f"file://{folder}"
    return base.rstrip("/")


def new_id(prefix: str) -> str:
    return f"{prefix}-{uuid.uuid4().hex[:10]}"


def file_system(spark: SparkSession, path: str):
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), p


def data_files(spark: SparkSession, path: str) -> list[tuple[str, int]]:
    """(path, bytes) of the data files directly in a folder; none if there is no folder."""
    fs, p = file_system(spark, path)
    if not fs.exists(p):
        return []
    return [(f.getPath().toString(), f.getLen()) for f in fs.listStatus(p) if f.isFile() and not f.getPath().getName().startswith(("_", "."))]


def delete(spark: SparkSession, path: str) -> None:
    fs, p = file_system(spark, path)
    fs.delete(p, True)


def measured(spark: SparkSession, p: Physical) -> Physical:
    """`p` with files and bytes as they are."""
    from dataclasses import replace

    found = data_files(spark, p.path)
    return replace(p, files=len(found), bytes=sum(n for _, n in found))


def read_physical(spark: SparkSession, tables: Sequence[Physical], types: dict[str, str], columns: Sequence[str], extra: Sequence[str] = ()) -> DataFrame:
    """One scan over files of one layout: keys and the wanted logical columns. extra: expressions on hidden metadata."""
    entry = {logical_name(c): stored_name(c) for c in tables[0].columns}
    wanted = [c for c in columns if c not in KEYS]
    ddl = ", ".join([*(f"`{k}` string" for k in KEYS), *dict.fromkeys(f"`{entry[c]}` {types[c]}" for c in wanted)])
    rows = spark.read.schema(ddl).parquet(*(t.path for t in tables))
    return rows.selectExpr(*KEYS, *(f"`{entry[c]}` as `{c}`" for c in wanted), *extra)


def range_of(column: str = "entity_id"):
    """The place of an id in the hash space [0, 2**32): the first 32 bits of md5."""
    return F.conv(F.substring(F.md5(F.col(column)), 1, 8), 16, 10).cast("long")


def write_by_batch(df: DataFrame, path: str, sort: Sequence[str], target_mb: int = 128, label: str = "_b", source: str = BATCH, options: dict[str, str] | None = None) -> None:
    """Write one folder a value of `source`, rows sorted within files, by as many tasks as the bytes need.

    Rows are rebalanced by that value: what belongs to a large one is dealt to several tasks of some `target_mb` (less
    where cores would idle), small ones share a task. The plan's own size estimate sets the target, so no pass is spent.
    """
    spark = df.sparkSession
    estimate = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    share = max(1 << 20, min(target_mb << 20, estimate // (2 * spark.sparkContext.defaultParallelism)))
    settings = {"spark.sql.adaptive.enabled": "true", "spark.sql.adaptive.advisoryPartitionSizeInBytes": str(share), "spark.sql.adaptive.rebalancePartitionsSmallPartitionFactor": "0.5", "spark.sql.adaptive.coalescePartitions.initialPartitionNum": "256"}
    rows = df if label in df.columns else df.withColumn(label, F.col(source))
    rows = rows.hint("rebalance", F.col(label)).sortWithinPartitions(label, *(c for c in sort if c != label))
    writer = with_settings(rows, settings).write.option("compression", "zstd").partitionBy(label)
    for k, v in (options or {}).items():
        writer = writer.option(k, v)
    writer.parquet(path)


def with_settings(df: DataFrame, settings: dict[str, str]) -> DataFrame:
    """`df` in a session of its own with other settings for its plan (scans keep to the session that made them)."""
    from ..plans.translate import in_session, own_session

    return in_session(own_session(df.sparkSession, settings), df)
