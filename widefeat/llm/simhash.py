"""Operator 10: SimHash near duplicates with pigeonring filtering.

A fingerprint's 64 bits are a ring of `segments` parts. If two fingerprints differ in at most t bits, some part
starts a chain in which every prefix of l parts differs in at most l * t / segments bits. The first parts of that
chain (those whose budget is below one bit) are therefore equal: they are the join key. Candidates must then keep
within the budget of every longer prefix before the full Hamming distance is taken.

Only distinct fingerprints take part, each once. A key shared by few fingerprints gives pairs. A key shared by many
(near copies by the thousand) gives none: each fingerprint is attached to the values one flip of its other bits away,
and those of one value are linked to the least of them. Two fingerprints at distance 2 meet in such a value, at
distance 1 or 2 all that meet are within 2, so no link's connection is lost and the work stays linear. (For t other
than 2 every key gives pairs.) Components come from minimum labels with pointer jumping over written tables.

Edge cases: null and empty texts and texts without a word have fingerprint zero and link like others; texts of fewer
words than a shingle are one shingle; repeated rows get the same component; null doc_ids never name a component
unless all of it are null; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, heavy_keys, ship, spread_join, staged, text_slices, unused

FEW = 16
BLOCK_WORDS = 50_000


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """The signed 64-bit SimHash over lower-cased (A to Z) word shingles, hashed by XXH64 with seed 42."""
    from xxhash import xxh64_intdigest

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    ones, total = np.zeros(64, dtype=np.int64), 0
    last = max(1, len(words) - shingle + 1)
    for a in range(0, last, BLOCK_WORDS):
        block = words[a : min(last, a + BLOCK_WORDS) + shingle - 1]
        grams = map(b" ".join, zip(*(block[k:] for k in range(shingle)), strict=False)) if len(words) >= shingle else [b" ".join(words)]
        hashes = np.fromiter((xxh64_intdigest(g, 42) for g in grams), dtype="<u8")
        ones += bits_set(hashes)
        total += len(hashes)
    return majority(ones, total)


def bits_set(hashes: np.ndarray) -> np.ndarray:
    """In how many of the 64-bit hashes each bit is set."""
    return np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)


def majority(ones: np.ndarray, total: int) -> int:
    """The signed fingerprint: bits set in over half of the hashes."""
    return int(np.packbits(2 * ones > total, bitorder="little").view("<i8")[0])


def fingerprints(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """doc_id, text_hash and fp (the fingerprint as a signed long) of every whole text."""
    ship(docs.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in (p for b in batches for p in text_slices(b)):
            fps = pa.array([fingerprint(t, shingle) for t in part.column("text").to_pylist()], pa.int64())
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text_hash"), fps], ["doc_id", "text_hash", "fp"])

    text = F.col("text").cast("string")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("text_hash"), text.alias("text")).mapInArrow(run, "doc_id long, text_hash long, fp long")


def signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


class Ring:
    """The ring of parts: masks, and how many bits a chain's prefix may differ in."""

    def __init__(self, segments: int, most_bits: int):
        if not (0 <= most_bits <= 64 and 0 < segments <= 64):
            raise ValueError("a ring has 1 to 64 segments and at most 64 differing bits")
        edges = [64 * i // segments for i in range(segments + 1)]
        self.parts = [((1 << b) - (1 << a)) for a, b in zip(edges, edges[1:], strict=False)]
        self.segments, self.most_bits = segments, most_bits
        self.exact = max(k for k in range(segments + 1) if k * most_bits < segments)

    def chain(self, start: int, length: int) -> int:
        mask = 0
        for k in range(length):
            mask |= self.parts[(start + k) % self.segments]
        return mask

    def keeps(self, difference: Column, start: int) -> Column:
        """Whether every prefix of the chain from `start` stays within its proportional budget."""
        ok = F.lit(True)
        for k in range(self.exact + 1, self.segments + 1):
            ok &= F.bit_count(difference.bitwiseAND(F.lit(signed(self.chain(start, k))))) <= k * self.most_bits // self.segments
        return ok

    def may_link(self, difference: Column) -> Column:
        """Whether some chain keeps within its budgets and all bits within the radius."""
        chains = F.lit(False)
        for start in range(self.segments):
            first = F.bit_count(difference.bitwiseAND(F.lit(signed(self.chain(start, max(1, self.exact))))))
            chains |= (first <= max(1, self.exact) * self.most_bits // self.segments) & self.keeps(difference, start)
        return chains & (F.bit_count(difference) <= self.most_bits)


def linked(distinct: DataFrame, most_bits: int = 2, segments: int = 7) -> DataFrame:
    """Pairs (a, b) of distinct fingerprints `fp`, enough to connect all that link at `most_bits` or fewer bits."""
    ring = Ring(segments, most_bits)
    if not ring.exact:
        raise ValueError("segments must exceed most_bits, or no part of the chain is a join key")
    keys = F.array(*(F.struct(F.lit(i).alias("start"), F.col("fp").bitwiseAND(F.lit(signed(ring.chain(i, ring.exact)))).alias("key")) for i in range(segments)))
    rows = distinct.select("fp", F.inline(keys))
    shared = staged(rows.groupBy("start", "key").agg(F.count("*").alias("n")).where("n > 1"), "ring-keys")
    few = F.col("n") <= FEW if most_bits == 2 else F.lit(True)
    members = staged(spread_join(rows, shared, ["start", "key"]), "ring-members")
    left, right = (members.where(few).select("start", "key", F.col("fp").alias(side)) for side in "ab")
    difference = F.col("a").bitwiseXOR(F.col("b"))
    within = F.coalesce(*(F.when(F.col("start") == i, ring.keeps(difference, i)) for i in range(segments)))
    pairs = left.join(right, ["start", "key"]).where((F.col("a") < F.col("b")) & within & (F.bit_count(difference) <= most_bits)).select("a", "b")
    if most_bits != 2:
        return pairs.distinct()
    loose = F.coalesce(*(F.when(F.col("start") == i, F.lit(signed(~ring.chain(i, ring.exact) & (1 << 64) - 1))) for i in range(segments)))
    crowded = members.where(~few).groupBy("fp").agg(F.bit_or(loose).alias("loose"))
    flips = F.filter(F.array(*(F.lit(f) for f in [0, *(signed(1 << b) for b in range(64))])), lambda f: f.bitwiseAND(F.col("loose")) == f)
    near = crowded.select("fp", F.explode(flips).alias("flip")).select("fp", F.col("fp").bitwiseXOR(F.col("flip")).alias("value"))
    least = near.groupBy("value").agg(F.min("fp").alias("a"), F.count("*").alias("n")).where("n > 1").drop("n")
    stars = near.join(least, "value").where(F.col("fp") != F.col("a")).select("a", F.col("fp").alias("b"))
    return pairs.union(stars).distinct()


def connect(edges: DataFrame) -> DataFrame:
    """node and label (its component's least node) for all nodes of the edges (a, b)."""
    both = staged(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))), "links")
    labels = staged(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.col("node")).alias("label")), "labels")
    hubs = heavy_keys(both, ["b"]) or False
    while True:
        heard = spread_join(both, labels.select(F.col("node").alias("b"), "label"), "b", heavy=hubs).groupBy("a").agg(F.min("label").alias("heard"))
        stepped = staged(labels.join(heard, labels.node == heard.a, "left").select("node", "label", F.least("label", "heard").alias("next")), "stepped")
        jump = stepped.select(F.col("node").alias("next"), F.col("next").alias("beyond"))
        moved = staged(spread_join(stepped, jump, "next", "left").select("node", F.col("label").alias("old"), F.least("next", F.coalesce("beyond", "next")).alias("label")), "labels")
        discard(labels, stepped)
        labels = moved
        if moved.where("old <> label").isEmpty():
            discard(both)
            return labels.select("node", "label")


def near_duplicates(docs: DataFrame, shingle: int = 3, most_bits: int = 2, segments: int = 7) -> DataFrame:
    """doc_id, text_hash, fp, component (its least fingerprint) and component_id (its smallest doc_id) of every document."""
    fps = staged(fingerprints(docs, shingle), "fingerprints")
    distinct = staged(fps.groupBy("fp").agg(F.min("doc_id").alias("least_id")), "distinct")
    labels = connect(linked(distinct, most_bits, segments))
    named = staged(distinct.join(labels, distinct.fp == labels.node).select("fp", "least_id", "label"), "named")
    component = named.groupBy("label").agg(F.min("least_id").alias("of_label"))
    renamed = spread_join(named, component, "label").select("fp", "label", "of_label")
    ids = distinct.join(renamed, "fp", "left").select("fp", F.coalesce("label", "fp").alias("component"), F.coalesce("of_label", "least_id").alias("component_id"))
    return spread_join(fps, ids, "fp").select("doc_id", "text_hash", "fp", "component", "component_id")


def one_of_each(docs: DataFrame, **options) -> DataFrame:
    """The documents without all but one of each component: the smallest doc_id (nulls last), then the smallest text hash stays."""
    return least_of_each(docs, near_duplicates(docs, **options))


def least_of_each(docs: DataFrame, grouped: DataFrame) -> DataFrame:
    """The documents that stay, by `grouped` (doc_id, text_hash, component): the least of each component."""
    rows = staged(grouped.select("component", F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "text_hash").alias("place")), "grouped")
    stays = rows.groupBy("component").agg(F.min("place").alias("stays"))
    gone_id, gone_hash, twin = (unused(docs, c) for c in ("gone_id", "gone_hash", "twin"))
    gone = spread_join(rows, stays, "component").where("place <> stays").select(F.col("place.doc_id").alias(gone_id), F.col("place.text_hash").alias(gone_hash)).distinct()
    text_hash = F.xxhash64(F.col("text").cast("string"))
    kept = docs.join(gone, F.col("doc_id").cast("long").eqNullSafe(F.col(gone_id)) & (text_hash == F.col(gone_hash)), "left_anti")
    if rows.groupBy("place").count().where("count > 1").isEmpty():
        return kept
    return kept.select("*", text_hash.alias(twin)).dropDuplicates(["doc_id", twin]).drop(twin)  # rows equal in id and text: one of them
