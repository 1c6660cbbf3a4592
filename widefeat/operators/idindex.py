"""The global id index: entity_id to the files that hold its row, in hash buckets sorted by id.

Segments are added for physical tables that aren't covered yet; what no segment covers is scanned, so a lookup is
right at any coverage. A segment has as many buckets as its rows need; a lookup reads the buckets of its ids, sorted by id
so that row groups and pages of others are skipped, then only the files they name, in which the pushed id filter skips
row groups again (bulk and compacted files are sorted by id).
"""

from __future__ import annotations

import math
import threading
from collections.abc import Sequence
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import BATCH, ID, KEYS, Physical
from ..plans import translate
from .storage import file_system, new_id, range_of

BUCKET_ROWS = 2_000_000
FOLDERS = 5_000
SEGMENT = f"{ID} string, {BATCH} string, phys_id string, file string"


class IdIndex:
    """Index of one engine's tables."""

    def __init__(self, engine, bucket_rows: int = BUCKET_ROWS):
        self.engine, self.bucket_rows, self.lock = engine, bucket_rows, threading.Lock()

    def covered(self, table: str) -> dict[str, str]:
        return {r["phys_id"]: r["location"] for r in self.engine.catalog.store.query("select phys_id, location from index_segments where path = ?", table)}

    def catch_up(self, table: str, batches: Sequence[str] | None = None) -> int:
        """Cover all current base tables (of some batches); the number of newly covered ones."""
        engine, spark = self.engine, self.engine.spark
        snap, known = engine.catalog.snapshot(table), self.covered(table)
        todo = [p for p in snap.physical if p.purpose in ("core", "features") and p.phys_id not in known and (batches is None or p.batch in batches)]
        if not todo:
            return 0
        for i in range(0, len(todo), FOLDERS):  # the folders of a segment are broadcast, so their number is bounded
            self._segment(table, snap.version, todo[i : i + FOLDERS])
        return len(todo)

    def _segment(self, table: str, version: int, todo: Sequence[Physical]) -> None:
        """Write one segment for some physical tables and register it."""
        engine, spark = self.engine, self.engine.spark
        folders = spark.createDataFrame([(p.path.rstrip("/") + "/", p.phys_id) for p in todo], "folder string, phys_id string")
        rows = spark.read.schema(f"{ID} string, {BATCH} string").parquet(*(p.path for p in todo)).select(*KEYS, F.col("_metadata.file_path").alias("file"))
        # one row a folder: joined on the folder part of the file's path, with escapes undone on both sides
        plain = lambda c: F.regexp_replace(F.url_decode(F.regexp_replace(c, r"\+", "%2B")), r"^file:/+", "/")
        keyed = rows.withColumn("folder", F.regexp_replace(plain(F.col("file")), r"[^/]+$", "")).join(F.broadcast(folders.withColumn("folder", plain(F.col("folder")))), "folder")
        buckets = 1 << max(0, math.ceil(math.log2(max(1, sum(p.rows for p in todo) / self.bucket_rows))))
        path = f"{engine.root}/{table}/index/{new_id('seg')}-{buckets}"
        bucket = (range_of() * buckets / F.lit(1 << 32)).cast("int")
        keyed.select(*KEYS, "phys_id", "file", bucket.alias("bucket")).repartition(buckets, "bucket").sortWithinPartitions("bucket", ID).write.option("compression", "zstd").partitionBy("bucket").parquet(path)
        with engine.catalog.store.transaction():
            for p in todo:
                engine.catalog.store.execute("insert into index_segments values (?, ?, ?, ?, ?)", table, p.phys_id, path, p.rows, version)

    def coverage(self, table: str) -> float:
        """Share of base tables' rows that the index covers."""
        snap, known = self.engine.catalog.snapshot(table), self.covered(table)
        base = [p for p in snap.physical if p.purpose in ("core", "features")]
        return sum(p.rows for p in base if p.phys_id in known) / max(1, sum(p.rows for p in base))

    def locate(self, table: str, ids: Sequence[str]) -> DataFrame:
        """Index rows of some ids in one scan: of each segment only the buckets that can have them."""
        spark, folders = self.engine.spark, []
        for path in sorted(set(self.covered(table).values())):
            buckets = int(path.rpartition("-")[2])
            for b in sorted({translate.hash_place(i) * buckets >> 32 for i in ids}):
                folder = f"{path}/bucket={b}"
                fs, at = file_system(spark, folder)
                if fs.exists(at):  # no id fell into it
                    folders.append(folder)
        if not folders:
            return spark.createDataFrame([], SEGMENT)
        return spark.read.schema(SEGMENT).parquet(*folders).where(F.col(ID).isin(list(ids)))

    def narrowed(self, table: str, snap, ids: Sequence[str]):
        """The snapshot with covered tables reduced to the files of the ids, and the batches that can have them."""
        known = self.covered(table)
        files: dict[str, set[str]] = {}
        for r in self.locate(table, ids).groupBy("phys_id").agg(F.collect_set("file").alias("files")).collect() if len(ids) > 1 else self.locate(table, ids).select("phys_id", F.array("file").alias("files")).collect():
            files.setdefault(r.phys_id, set()).update(r.files)
        kept: list[Physical] = []
        for p in snap.physical:
            if p.phys_id not in known or p.purpose not in ("core", "features"):
                kept.append(p)
            else:
                kept += [replace(p, path=f, bytes=p.bytes // max(1, p.files), files=1) for f in sorted(files.get(p.phys_id, ()))]
        narrow = replace(snap, physical=tuple(kept))
        batches = tuple(dict.fromkeys(p.batch for p in kept if p.purpose == "core"))
        return narrow, batches, sum(map(len, files.values()))
