"""Operator 8: contiguous shards of equal bytes, from global prefix sums.

Rows (without their texts) are dealt into ranges of ascending doc_id; each range adds up its own sizes, the ranges'
totals (one row a range) give every row its place in the whole, and equal targets of bytes cut the line. A row
belongs to the shard that holds its middle byte, so shards are contiguous and differ from the target by less than
one row at either end. Law: `bytes`.

Edge cases: null text has size 1 and crc32 0; null doc_ids come first, equal doc_ids and repeated rows are ordered
by text hash and position in the input; an empty table gives no rows; shards may be empty when rows are fewer.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ship, staged

RANGED = "part int, doc_id long, size long, text_crc32 long, local_start long, local_row long"


def running_sums(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Bytes and rows of this partition before each row."""
    from pyspark import TaskContext

    part, start, row = TaskContext.get().partitionId(), 0, 0
    for b in batches:
        size = b.column("size").to_numpy(zero_copy_only=False)
        n, starts = len(size), start + np.cumsum(size) - size
        yield pa.RecordBatch.from_arrays([pa.array(np.full(n, part, np.int32)), *(b.column(c) for c in ("doc_id", "size", "text_crc32")), pa.array(starts), pa.array(np.arange(row, row + n))], ["part", "doc_id", "size", "text_crc32", "local_start", "local_row"])
        start, row = start + int(size.sum()), row + n


def shard_of(middle: Column, shards: int, total: int) -> Column:
    """The shard of a row whose doubled middle byte is `middle`, by comparing with the exact integer bounds of the shards."""
    bounds = [F.lit(-(-2 * total * k // shards)) for k in range(1, shards)]
    return sum(((middle >= b).cast("int") for b in bounds), F.lit(0))


def shard_by_bytes(docs: DataFrame, shards: int = 8) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard (null under this law)."""
    spark = docs.sparkSession
    ship(spark)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("tie"), F.monotonically_increasing_id().alias("position"))
    keys = ("doc_id", "tie", "position")
    ranges = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ordered = rows.repartitionByRange(ranges, *keys).sortWithinPartitions(*keys).select("doc_id", "size", "text_crc32")
    ranged = staged(ordered.mapInArrow(running_sums, RANGED), "ranges")
    starts, bytes_before, rows_before = [], 0, 0
    for t in ranged.groupBy("part").agg(F.sum("size").alias("bytes"), F.count("*").alias("n")).orderBy("part").collect():
        starts.append((t.part, bytes_before, rows_before))
        bytes_before, rows_before = bytes_before + t.bytes, rows_before + t.n
    offsets = spark.createDataFrame(starts, "part int, bytes_before long, rows_before long")
    middle = 2 * (F.col("bytes_before") + F.col("local_start")) + F.col("size")
    placed = ranged.join(offsets, "part").select(
        "doc_id", "size", "text_crc32", (F.col("rows_before") + F.col("local_row")).alias("row"),
        shard_of(middle, shards, bytes_before).alias("shard"),
    )
    first = {r.shard: r.first for r in placed.groupBy("shard").agg(F.min("row").alias("first")).collect()}
    slot = F.col("row") - F.element_at(F.array(*(F.lit(first.get(k, 0)).cast("long") for k in range(shards))), F.col("shard") + 1)
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", slot.alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
