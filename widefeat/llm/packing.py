"""Operator 3: packing by minimum bin slack.

A document's ids (with the end id) are cut into full windows and a rest. From the counts of the lengths alone (at
most `capacity` numbers, whatever the corpus's size) the driver plans windows: the longest length left opens a
window, a bitset subset-sum over the other lengths left finds the fill closest to capacity, backtracking gives how
many pieces of each length it takes, and the window is repeated as often as the counts allow. A piece then finds its
place from its length and its rank among the pieces of that length; ranks come from per-shard counts and prefix sums,
so no window, sort or group of pieces ever meets in one task.

Edge cases: null text counts as empty (one piece with the end id); repeated and null doc_ids are packed like others;
an empty table gives no rows; extra columns are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import ship, staged, text_slices
from .tokens import library_encoder, tokenizer_path

CAPACITY = 2048
PIECES = "shard int, doc_id long, start long, length long, ids_crc32 long, doc_tokens long, local_rank long"
PLACED = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


@dataclass(frozen=True)
class Pattern:
    """`times` windows, each with `take[i][1]` pieces of length `take[i][0]`."""

    take: tuple[tuple[int, int], ...]
    times: int


def closest_fill(counts: dict[int, int], lengths: list[int], target: int) -> dict[int, int]:
    """The multiset of available lengths with the largest sum up to target. lengths: descending keys of counts."""
    mask, reach, trail = (1 << (target + 1)) - 1, 1, []
    for length in lengths:
        if length > target:
            continue
        left, step = min(counts[length], target // length), 1
        while left and not reach >> target & 1:
            k = min(step, left)
            trail.append((reach, length, k))
            reach |= reach << (k * length) & mask
            left, step = left - k, step * 2
        if reach >> target & 1:
            break
    best, used = reach.bit_length() - 1, {}
    for before, length, k in reversed(trail):
        if not before >> best & 1:
            best -= k * length
            used[length] = used.get(length, 0) + k
    return used


def plan_windows(counts: dict[int, int], capacity: int = CAPACITY) -> list[Pattern]:
    """Windows that hold every piece exactly once, from the number of pieces of each length."""
    left = {n: c for n, c in counts.items() if c > 0}
    lengths, patterns = sorted(left, reverse=True), []
    while lengths:
        seed = lengths[0]
        left[seed] -= 1
        take = closest_fill(left, lengths, capacity - seed)
        left[seed] += 1
        take[seed] = take.get(seed, 0) + 1
        times = min(left[n] // k for n, k in take.items())
        patterns.append(Pattern(tuple(sorted(take.items(), reverse=True)), times))
        for n, k in take.items():
            left[n] -= k * times
        lengths = [n for n in lengths if left[n]]
    return patterns


@dataclass(frozen=True)
class Runs:
    """The plan by length and rank: sorted keys and, for each, pieces a window, first window and offset there."""

    key: np.ndarray
    low: np.ndarray
    each: np.ndarray
    sequence: np.ndarray
    offset: np.ndarray

    SPREAD = 1 << 50

    @classmethod
    def of(cls, patterns: list[Pattern]) -> Runs:
        rows, seen, sequence = [], {}, 0
        for p in patterns:
            offset = 0
            for length, k in p.take:
                low = seen.get(length, 0)
                rows.append((length * cls.SPREAD + low, low, k, sequence, offset))
                seen[length], offset = low + k * p.times, offset + k * length
            sequence += p.times
        table = np.asarray(sorted(rows) or np.zeros((0, 5)), dtype=np.int64).reshape(-1, 5)
        return cls(*(np.ascontiguousarray(c) for c in table.T))

    def place(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = np.searchsorted(self.key, length * self.SPREAD + rank, side="right") - 1
        window, nth = np.divmod(rank - self.low[at], self.each[at])
        return self.sequence[at] + window, self.offset[at] + nth * length


def cut_partition(path: str, end_id: int, capacity: int):
    """A mapInArrow function: a row per piece, with its rank among this partition's pieces of its length."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encoder, shard, seen = library_encoder(path), TaskContext.get().partitionId(), np.zeros(capacity + 1, np.int64)
        end = np.asarray([end_id], dtype="<u4").tobytes()
        for part in (p for b in batches for p in text_slices(b)):
            doc, start, length, crc, total = [], [], [], [], []
            for doc_id, ids in zip(part.column("doc_id").to_pylist(), encoder.encode(part.column("text").to_pylist()), strict=True):
                ids += end
                for a in range(0, len(ids), 4 * capacity):
                    piece = ids[a : a + 4 * capacity]
                    doc.append(doc_id)
                    start.append(a // 4)
                    length.append(len(piece) // 4)
                    crc.append(zlib.crc32(piece))
                    total.append(len(ids) // 4)
            rank = []
            for n in length:
                rank.append(int(seen[n]))
                seen[n] += 1
            columns = (doc, start, length, crc, total, rank)
            yield pa.RecordBatch.from_arrays([pa.array([shard] * len(doc), pa.int32()), *(pa.array(c, pa.int64()) for c in columns)], ["shard", "doc_id", "start", "length", "ids_crc32", "doc_tokens", "local_rank"])

    return run


def pack(docs: DataFrame, end_id: int = 1, capacity: int = CAPACITY, tokenizer: str | None = None) -> DataFrame:
    """Pack `docs` (doc_id, text) into sequences of at most `capacity` ids: a row per piece.

    Columns: doc_id, start, length, ids_crc32, doc_tokens, sequence_id (gapless from 0), offset.
    """
    ship(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    pieces = staged(rows.mapInArrow(cut_partition(tokenizer or tokenizer_path(), end_id, capacity), PIECES), "pieces")
    by_shard = pieces.groupBy("length", "shard").agg(F.count("*").alias("n"))
    counts = {r.length: r.n for r in pieces.groupBy("length").count().withColumnRenamed("count", "n").collect()}
    runs = docs.sparkSession.sparkContext.broadcast(Runs.of(plan_windows(counts, capacity)))
    before = Window.partitionBy("length").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    first = by_shard.select("length", "shard", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("first"))

    def place(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            length, rank = (b.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("length", "rank"))
            sequence, offset = runs.value.place(length, rank) if len(length) else (length, rank)
            names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in names), pa.array(sequence), pa.array(offset)], [*names, "sequence_id", "offset"])

    ranked = pieces.join(first, ["length", "shard"]).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", (F.col("first") + F.col("local_rank")).alias("rank"))
    return ranked.mapInArrow(place, PLACED)


def padding_share(packed: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """One row: sequences, ids, padding ids and their share; a sequence whose length is a power of two isn't padded."""
    used = packed.groupBy("sequence_id").agg(F.sum("length").alias("used"))
    pad = F.when(F.expr("(used & (used - 1)) = 0"), 0).otherwise(capacity - F.col("used"))
    return used.agg(F.count("*").alias("sequences"), F.sum("used").alias("ids"), F.sum(pad).alias("padding")).withColumn("share", F.col("padding") / (F.col("ids") + F.col("padding")))
