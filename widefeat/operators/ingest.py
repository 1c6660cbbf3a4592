"""Adding rows: adapt, normalise, stamp ids and batch, drop repeats, write, commit.

Files become visible only by the commit of their batch; a failure before it deletes what was written.
"""

from __future__ import annotations

import json
import time
from collections.abc import Sequence

from pyspark.sql import Column as SparkColumn
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..catalog import Catalog
from ..model import BATCH, ID, KEYS, BatchEntry, Column, ConflictError, Physical
from ..sources.adapters import SourceSpec, adapt
from .storage import delete, file_system, measured, new_id, write_by_batch


def id_column(strategy: str | tuple, payload: str) -> SparkColumn:
    """content: md5 of the payload; uuid: random; ("key", columns): md5 of the joined key."""
    if strategy == "content":
        return F.md5(F.coalesce(F.col(payload).cast("string"), F.lit("")))
    if strategy == "uuid":
        return F.expr("uuid()")
    return F.md5(F.concat_ws("\x1f", *(F.coalesce(F.col(c).cast("string"), F.lit("\x00")) for c in strategy[1])))


def normalize(rows: DataFrame, columns: Sequence[Column], mapping: dict[str, str], id_strategy: str | tuple, batch: str, payload: str = "payload") -> DataFrame:
    """Logical columns from source expressions; unmapped source columns go, missing ones are NULL.

    mapping: logical column to SQL expression over the source; `payload` and `source_key` may be mapped for ids and ties;
    `batch` is an SQL expression too, so one pass can hold many batches.
    """
    known = {c.name: c for c in columns if c.kind == "stage"}
    fields = [(F.expr(mapping[n]) if n in mapping else F.lit(None)).cast(c.type).alias(n) for n, c in known.items()]
    helpers = [F.expr(mapping.get("payload", "''")).alias("_payload"), F.expr(mapping.get("source_key", "0")).alias("_key")]
    keyed = rows if id_strategy in ("content", "uuid") else rows.withColumn("_id", id_column(id_strategy, payload))
    ids = [F.col("_id")] if "_id" in keyed.columns else []
    out = keyed.select(*ids, F.coalesce(F.expr(batch).cast("string"), F.lit("unknown")).alias(BATCH), *fields, *helpers)
    stamped = F.col("_id") if ids else id_column(id_strategy, "_payload")
    return out.select(stamped.alias(ID), BATCH, *known, "_key")


def deduplicate(rows: DataFrame, on_conflict: str) -> DataFrame:
    """In a batch one row an id, the smallest source key; keep_first: over all batches at hand, the first batch by source key.

    An aggregate that combines before the shuffle, so a payload that is repeated very often never meets in one task.
    """
    keys = [ID] if on_conflict == "keep_first" else list(KEYS)
    rest = [c for c in rows.columns if c not in keys]
    first = rows.groupBy(*keys).agg(F.min_by(F.struct(*rest), F.struct("_key", BATCH)).alias("_row"))
    return first.select(*keys, "_row.*").select(*rows.columns)


def ingest(
    spark: SparkSession, catalog: Catalog, root: str, source: SourceSpec, table: str, batch: str, mapping: dict[str, str], *,
    id_strategy: str | tuple = "content", mode: str = "bulk", dedup: bool = True, on_conflict: str = "keep_first", create: Sequence[Column] | None = None,
    many: bool = False, target_mb: int = 128, known_ids=None, fail_before_commit: bool = False,
) -> list[BatchEntry]:
    """Ingest one batch (named `batch`) or, with many, one batch for each value of the expression `batch`.

    Rows that can't be parsed go to the table's quarantine folder. known_ids(spark) gives the committed (entity_id) rows for keep_first across batches; if another ingestion commits
    meanwhile, the comparison is made again before the next try.
    """
    if create is not None and not catalog.exists(table):
        catalog.create_table(table, create)
    snap = catalog.snapshot(table)
    rows, bad = adapt(spark, source)
    if bad is not None and not bad.isEmpty():
        bad.write.text(f"{root}/{table}/quarantine/{new_id('q')}")
    expr = batch if many else "'" + batch.replace("'", "\\'") + "'"
    rows = normalize(rows, snap.columns, mapping, id_strategy, expr)
    if dedup and id_strategy != "uuid":
        rows = deduplicate(rows, on_conflict)
    for attempt in range(5):
        snap = catalog.snapshot(table)
        fresh = rows
        if dedup and on_conflict == "keep_first" and id_strategy != "uuid" and known_ids is not None and snap.batches:
            fresh = rows.join(known_ids(spark), ID, "left_anti")
        staging = f"{root}/{table}/core/{new_id('s')}"
        try:
            with catalog.store.writing(table, "core", staging):
                entries = _write(spark, catalog, fresh.drop("_key"), table, staging, batch, many, source, mapping, id_strategy, mode, target_mb)
            if fail_before_commit:
                raise RuntimeError("injected failure")
            catalog.register_batches(table, entries, expected=snap.version)
            return [e[0] for e in entries]
        except ConflictError:
            delete(spark, staging)
            if attempt == 4:
                raise
        except BaseException:
            delete(spark, staging)
            raise
    return []


def _write(spark, catalog, rows, table, staging, batch, many, source, mapping, id_strategy, mode, target_mb):
    """Write one folder a batch and describe what is there."""
    columns = [c for c in catalog.snapshot(table).columns if c.kind == "stage"]
    if mode == "bulk":
        write_by_batch(rows if many else rows.withColumn("_b", F.lit("0")), staging, [ID], target_mb, "_b", BATCH if many else "_b")
    elif many:
        rows.withColumn("_b", F.col(BATCH)).write.option("compression", "zstd").partitionBy("_b").parquet(staging)
    else:
        rows.write.option("compression", "zstd").parquet(f"{staging}/_b=0")
    if not many:
        file_system(spark, f"{staging}/_b=0")[0].mkdirs(file_system(spark, f"{staging}/_b=0")[1])  # an empty batch has a folder too
    written = spark.read.schema(f"{BATCH} string").parquet(staging if many else f"{staging}/_b=0").groupBy(BATCH).agg(F.count("*").alias("n"))
    counts = ({} if many else {batch: 0}) | {r[BATCH]: r.n for r in written.collect()}
    filled = [c.name for c in columns if c.name in mapping]
    absent = [c.name for c in columns if c.name not in mapping]
    entries = []
    for name, n in sorted(counts.items(), key=lambda x: (len(x[0]), x[0])):
        folder = f"{staging}/_b={escaped(spark, name) if many else 0}"
        p = measured(spark, Physical(new_id("core"), "core", folder, name, tuple(c.name for c in columns), "core", n, sorted_by=ID if mode == "bulk" else ""))
        entries.append((BatchEntry(name, n, 0, source.describe(), json.dumps(mapping), json.dumps(id_strategy), time.time()), [p], filled, absent))
    return entries


def escaped(spark: SparkSession, name: str) -> str:
    return spark.sparkContext._jvm.org.apache.spark.sql.catalyst.catalog.ExternalCatalogUtils.escapePathName(name)

