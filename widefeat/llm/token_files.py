"""Operator 1: token ids as Parquet list columns, with row groups, page indexes and encodings under control.

Layout: one file per shard, a shard being a range of ascending doc_id. Columns: shard, row, doc_id, n_tokens,
local_start (ids of the shard before the document) and ids (list of int). `ids` is dictionary-encoded (a vocabulary
of 49k entries bit-packs to two bytes an id), the ascending counters are delta-encoded (data page version 2), row
groups hold `row_group_mb` and pages `page_kb`; the writer adds column and offset indexes, so a reader that asks for
some doc_ids or for metadata only reads those pages. A second small table, the manifest, has one row per shard with
its first id in the whole stream.

Edge cases: null text counts as empty (only the end id is written); null doc_ids come first, equal doc_ids are
ordered by their text; an empty table gives files without rows; extra columns are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ship, staging_path, text_slices
from .tokens import library_encoder, tokenizer_path

FILE_SCHEMA = "shard int, row long, doc_id long, n_tokens int, local_start long, ids array<int>"
MANIFEST_SCHEMA = "shard int, first_doc_id long, last_doc_id long, n_docs long, n_tokens long, shard_start long, first_row long"


@dataclass(frozen=True)
class TokenFiles:
    """Where the token table and its manifest lie."""

    path: str
    manifest_path: str


def list_of_ids(encoded: list[bytes]) -> pa.ListArray:
    """Arrow lists over one buffer, without a Python object per id."""
    offsets = np.zeros(len(encoded) + 1, dtype=np.int32)
    np.cumsum([len(x) // 4 for x in encoded], out=offsets[1:])
    values = pa.Array.from_buffers(pa.int32(), int(offsets[-1]), [None, pa.py_buffer(b"".join(encoded))])
    return pa.ListArray.from_arrays(pa.array(offsets), values)


def ids_bytes(lists: pa.ListArray) -> Iterator[memoryview]:
    """The bytes of each list's ids, little-endian and unsigned."""
    values = lists.values.to_numpy(zero_copy_only=False).astype("<u4", copy=False)
    view, offsets = memoryview(values).cast("B"), lists.offsets.to_numpy()
    for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
        yield view[4 * a : 4 * b]


def encode_partition(path: str, end_id: int):
    """A mapInArrow function for a sorted partition: ids and the running count within it."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encoder, shard, row, start = library_encoder(path), TaskContext.get().partitionId(), 0, 0
        end = np.asarray([end_id], dtype="<u4").tobytes()
        for part in (p for b in batches for p in text_slices(b)):
            encoded = [x + end for x in encoder.encode(part.column("text").to_pylist())]
            counts = np.asarray([len(x) // 4 for x in encoded], dtype=np.int64)
            starts = start + np.cumsum(counts) - counts
            n = len(encoded)
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(n, shard, np.int32)), pa.array(np.arange(row, row + n)), part.column("doc_id"), pa.array(counts.astype(np.int32)), pa.array(starts), list_of_ids(encoded)],
                ["shard", "row", "doc_id", "n_tokens", "local_start", "ids"],
            )
            row, start = row + n, start + int(counts.sum())

    return run


def write_token_files(docs: DataFrame, end_id: int = 2, tokenizer: str | None = None, shards: int | None = None, row_group_mb: int = 64, page_kb: int = 256) -> TokenFiles:
    """Encode `docs` (doc_id, text) in ascending doc_id order and write token table and manifest to the shared folder."""
    spark = docs.sparkSession
    ship(spark)
    shards = shards or int(spark.conf.get("spark.sql.shuffle.partitions"))
    out = TokenFiles(staging_path(spark, "tokens"), staging_path(spark, "manifest"))
    ordered = (
        docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
        .withColumn("tie", F.xxhash64("text"))
        .repartitionByRange(shards, "doc_id", "tie")
        .sortWithinPartitions("doc_id", "tie", "text")
        .select("doc_id", "text")
    )
    writer = ordered.mapInArrow(encode_partition(tokenizer or tokenizer_path(), end_id), FILE_SCHEMA).write
    options = {"compression": "zstd", "parquet.block.size": row_group_mb << 20, "parquet.page.size": page_kb << 10, "parquet.writer.version": "v2", "parquet.enable.dictionary": "true"}
    options |= {f"parquet.enable.dictionary#{c}": "false" for c in ("row", "doc_id", "n_tokens", "local_start")}
    for k, v in options.items():
        writer = writer.option(k, v)
    writer.parquet(out.path)
    write_manifest(spark, out)
    return out


def write_manifest(spark: SparkSession, files: TokenFiles) -> None:
    """One row per shard, from metadata columns only; shards follow each other, so their totals add up to starts."""
    totals = (
        spark.read.schema(FILE_SCHEMA).parquet(files.path).groupBy("shard")
        .agg(F.min("doc_id").alias("first_doc_id"), F.max("doc_id").alias("last_doc_id"), F.count("*").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"))
        .orderBy("shard").collect()
    )
    rows, start, first = [], 0, 0
    for t in totals:
        rows.append((*t, start, first))
        start, first = start + t.n_tokens, first + t.n_docs
    spark.createDataFrame(rows, MANIFEST_SCHEMA).coalesce(1).write.parquet(files.manifest_path)


def read_manifest(spark: SparkSession, files: TokenFiles) -> DataFrame:
    return spark.read.schema(MANIFEST_SCHEMA).parquet(files.manifest_path)


def read_token_files(spark: SparkSession, files: TokenFiles, columns: tuple[str, ...] = ("doc_id", "n_tokens", "ids"), first_id: int | None = None, last_id: int | None = None) -> DataFrame:
    """Columns of the token table, with `start` in the whole stream; a doc_id range is pushed into the scan."""
    rows = spark.read.schema(FILE_SCHEMA).parquet(files.path)
    if first_id is not None:
        rows = rows.where(F.col("doc_id") >= first_id)
    if last_id is not None:
        rows = rows.where(F.col("doc_id") <= last_id)
    joined = rows.join(read_manifest(spark, files).select("shard", "shard_start"), "shard")
    return joined.select(*(c for c in columns if c != "start"), (F.col("shard_start") + F.col("local_start")).alias("start"))


def crc_of_ids(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Replace the column ids with their crc32."""
    for b in batches:
        at = b.schema.get_field_index("ids")
        kept = [i for i in range(b.num_columns) if i != at]
        crc = pa.array([zlib.crc32(x) for x in ids_bytes(b.column(at))], pa.int64())
        yield pa.RecordBatch.from_arrays([*(b.column(i) for i in kept), crc], [*(b.schema.names[i] for i in kept), "ids_crc32"])


def token_digest(docs: DataFrame, **options) -> DataFrame:
    """Write `docs` as token files, read them back whole: doc_id, start, n_tokens, ids_crc32."""
    spark = docs.sparkSession
    files = write_token_files(docs, **options)
    rows = spark.read.schema(FILE_SCHEMA).parquet(files.path).select("shard", "doc_id", "local_start", F.col("n_tokens").cast("long").alias("n_tokens"), "ids")
    crcs = rows.mapInArrow(crc_of_ids, "shard int, doc_id long, local_start long, n_tokens long, ids_crc32 long")
    starts = read_manifest(spark, files).select("shard", "shard_start")
    return crcs.join(starts, "shard").select("doc_id", (F.col("shard_start") + F.col("local_start")).alias("start"), "n_tokens", "ids_crc32")
