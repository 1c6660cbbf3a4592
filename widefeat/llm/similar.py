"""Near duplicates by SimHash fingerprints and exact similarity of word shingles: the pipeline's stage.

Two texts link if the Jaccard similarity of their sets of five-word shingles is 0.8 or more; of each connected group
one document stays. At that similarity some ten of 64 SimHash bits differ, so no part of a ring that wide can be a join
key (parts would have to be about three bits long). Texts therefore meet in bands of minima of seeded hashes (two texts
at 0.8 share no band of 48 with probability 1.5e-4); the pigeonring filter of operator 10 prunes the candidates by their
fingerprints, with a radius of 26 bits that a pair at 0.8 exceeds with probability below 1e-5; what is left is confirmed
on the whole sets. Equal sets are one node. In a band all members are compared with the least one; then, in bands of
several components, members outside the first's are compared with all by inverted indexes over cells of bounded size,
so a crowded band of near copies gives a star, pairs never become rows, and no connection is lost.

Edge cases: texts are lower-cased (A to Z) and split at blanks; those of fewer words than a shingle are one shingle;
null, empty and blank texts are one group; of rows equal in id and text one stays; extra columns of any name come along;
an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, ship, spread_join, staged, text_slices
from .simhash import BLOCK_WORDS, Ring, bits_set, connect, least_of_each, majority

SHINGLE, SIMILAR = 5, 0.8
BANDS, ROWS = 48, 8
BLOCK = 512
RADIUS, SEGMENTS = 26, 8
CELL, FAN = 256, 64
_odd = np.random.default_rng(17).integers(0, 1 << 64, (2, BANDS * ROWS), dtype=np.uint64)
FLIPS, FACTORS = _odd[0], _odd[1] | np.uint64(1)


def grams(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """Sorted distinct hashes of a text's word shingles."""
    from xxhash import xxh64_intdigest

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if len(words) < shingle:
        return np.array([xxh64_intdigest(b" ".join(words), 42)] if words else [], np.uint64)
    last, parts = len(words) - shingle + 1, []
    for a in range(0, last, BLOCK_WORDS):
        block = words[a : min(last, a + BLOCK_WORDS) + shingle - 1]
        joined = map(b" ".join, zip(*(block[k:] for k in range(shingle)), strict=False))
        parts.append(np.unique(np.fromiter((xxh64_intdigest(g, 42) for g in joined), np.uint64)))
    return parts[0] if len(parts) == 1 else np.unique(np.concatenate(parts))


def bands(found: np.ndarray) -> list[int]:
    """A key for each band of the set's minima; none for an empty set."""
    from xxhash import xxh64_intdigest

    if not len(found):
        return []
    least = np.full(BANDS * ROWS, (1 << 64) - 1, np.uint64)
    for a in range(0, len(found), BLOCK):
        np.minimum(least, ((found[a : a + BLOCK, None] ^ FLIPS) * FACTORS).min(axis=0), out=least)
    return [xxh64_intdigest(least[b * ROWS : (b + 1) * ROWS].tobytes(), b) for b in range(BANDS)]


def simhash(found: np.ndarray) -> int:
    """The fingerprint of a set of shingle hashes."""
    ones = np.zeros(64, np.int64)
    for a in range(0, len(found), BLOCK_WORDS):
        ones += bits_set(found[a : a + BLOCK_WORDS])
    return majority(ones, len(found))


def sketches(docs: DataFrame) -> DataFrame:
    """doc_id, text_hash, node (hash of the set), fp (its SimHash fingerprint) and band keys of every whole text."""
    ship(docs.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh3_64_intdigest

        for part in (p for b in batches for p in text_slices(b)):
            sets = [grams(t) for t in part.column("text").to_pylist()]
            nodes = np.array([xxh3_64_intdigest(s.tobytes()) for s in sets], np.uint64).view(np.int64)
            keys = [np.array(bands(s), np.uint64).view(np.int64) for s in sets]
            columns = [part.column("doc_id"), part.column("text_hash"), pa.array(nodes), pa.array([simhash(s) for s in sets], pa.int64()), pa.array(keys, pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "text_hash", "node", "fp", "bands"])

    text = F.col("text").cast("string")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("text_hash"), text.alias("text")).mapInArrow(run, "doc_id long, text_hash long, node long, fp long, bands array<long>")


def whole_sets(docs: DataFrame, chosen: DataFrame) -> DataFrame:
    """node and all its shingles, for the rows named by `chosen` (node, doc_id, text_hash)."""
    text = F.col("text").cast("string")
    rows = docs.select(F.col("doc_id").cast("long").alias("id"), F.xxhash64(text).alias("hash"), text.alias("text"))
    rows = rows.join(chosen, F.col("id").eqNullSafe(F.col("doc_id")) & (F.col("hash") == F.col("text_hash"))).select("node", "text")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in (p for b in batches for p in text_slices(b)):
            sets = [grams(t).view(np.int64) for t in part.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column("node"), pa.array(sets, pa.list_(pa.int64()))], ["node", "grams"])

    return rows.mapInArrow(run, "node long, grams array<long>").groupBy("node").agg(F.first("grams").alias("grams"))


def confirmed(pairs: DataFrame, sets: DataFrame, similar: float) -> DataFrame:
    """Those of the pairs (a, b) whose whole sets are at `similar` or more; a set `a` of many pairs is sent to many tasks."""
    fan = pairs.groupBy("a").agg(F.ceil(F.count("*") / FAN).cast("int").alias("fan"))
    dealt = spread_join(pairs, fan, "a").withColumn("salt", F.pmod(F.xxhash64("b"), F.col("fan")).cast("int")).drop("fan")
    right = sets.select(F.col("node").alias("b"), F.col("grams").alias("second"))
    left = sets.select(F.col("node").alias("a"), F.col("grams").alias("first")).join(fan, "a").select("a", "first", F.explode(F.sequence(F.lit(0), F.col("fan") - 1)).alias("salt"))
    sizes = F.size("first") + F.size("second")
    both = dealt.join(right, "b").join(left, ["a", "salt"]).where(F.least(F.size("first"), F.size("second")) >= similar * F.greatest(F.size("first"), F.size("second")) - 1e-6)
    return both.where(F.size(F.array_intersect("first", "second")) * (1 + similar) >= sizes * similar - 1e-6).select("a", "b")


def missing_links(cell: pa.Table, similar: float) -> pa.Table:
    """Links (a, b) between components of a cell (node, label, asks, grams): rows that ask against those that don't."""
    nodes, asks, lists = cell.column("node").to_numpy(), cell.column("asks").to_numpy(), cell.column("grams").combine_chunks()
    lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists
    sizes = lists.value_lengths().to_numpy()
    edges, owner = np.concatenate([[0], np.cumsum(sizes)]), np.repeat(np.arange(len(nodes)), sizes)
    _, ids = np.unique(lists.flatten().to_numpy(), return_inverse=True)
    held = np.flatnonzero(~asks[owner])
    held = held[np.argsort(ids[held], kind="stable")]
    n = np.bincount(ids[held], minlength=ids.max(initial=-1) + 1)
    holders, starts = owner[held], np.concatenate([[0], np.cumsum(n)])
    _, component = np.unique(cell.column("label").to_numpy(), return_inverse=True)
    found: list[tuple[int, int]] = []
    for x in np.flatnonzero(asks):
        mine = ids[edges[x] : edges[x + 1]]
        mine = mine[n[mine] > 0]
        if not len(mine):
            continue
        shared = np.bincount(np.concatenate([holders[starts[g] : starts[g + 1]] for g in mine]), minlength=len(nodes))
        for y in np.flatnonzero(~asks & (shared * (1 + similar) >= (sizes + sizes[x]) * similar - 1e-6)):
            if component[x] != component[y]:
                found.append((nodes[x], nodes[y]))
                component[component == component[y]] = component[x]
    return pa.table({"a": pa.array([a for a, _ in found], pa.int64()), "b": pa.array([b for _, b in found], pa.int64())})


def cells(mixed: DataFrame, sets: DataFrame) -> DataFrame:
    """Members of mixed bands (band, node, label, lead, n) dealt to cells of some CELL that ask and CELL that are asked, with their sets."""
    outside = mixed.where("label <> lead")
    blocks = outside.groupBy("band").agg(F.ceil(F.count("*") / CELL).cast("int").alias("blocks"))
    rows = spread_join(mixed, blocks, "band").withColumn("slices", F.ceil(F.col("n") / CELL).cast("int"))
    own = lambda parts: F.pmod(F.xxhash64("node"), F.col(parts)).cast("int")
    every = lambda parts: F.explode(F.sequence(F.lit(0), F.col(parts) - 1))
    asked = rows.select("band", own("slices").alias("slice"), every("blocks").alias("block"), "node", "label", F.lit(False).alias("asks"))
    asking = rows.where("label <> lead").select("band", every("slices").alias("slice"), own("blocks").alias("block"), "node", "label", F.lit(True).alias("asks"))
    return asked.union(asking).join(sets, "node")


def groups(docs: DataFrame, similar: float = SIMILAR) -> DataFrame:
    """doc_id, text_hash and component (its least node) of every document."""
    rows = staged(sketches(docs), "sketches")
    least = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "text_hash")
    chosen = rows.groupBy("node", "fp").agg(F.min(least).alias("p"), F.first("bands").alias("bands"))
    nodes = staged(chosen.select("node", "fp", "p.doc_id", "p.text_hash", "bands"), "nodes")
    keyed = nodes.select("node", "fp", F.explode("bands").alias("band"))
    met = staged(keyed.groupBy("band").agg(F.min(F.struct("node", "fp")).alias("first"), F.count("*").alias("n")).where("n > 1"), "met")
    members = staged(spread_join(keyed, met, "band"), "members")
    sets = staged(whole_sets(docs, nodes.join(members.select("node").distinct(), "node").select("node", "doc_id", "text_hash")), "sets")
    near = Ring(SEGMENTS, RADIUS).may_link(F.col("first.fp").bitwiseXOR(F.col("fp")))
    stars = staged(members.where((F.col("first.node") != F.col("node")) & near).select(F.col("first.node").alias("a"), F.col("node").alias("b")).distinct(), "pairs")
    links = staged(confirmed(stars, sets, similar), "stars")
    labels = connect(links)
    named = staged(members.join(labels, "node", "left").select("band", "node", "n", (F.col("node") == F.col("first.node")).alias("leads"), F.coalesce("label", "node").alias("label")), "named")
    told = staged(spread_join(named, named.where("leads").select("band", F.col("label").alias("lead")), "band"), "told")
    mixed = staged(spread_join(told, told.where("label <> lead").select("band").distinct(), "band"), "mixed")
    within = cells(mixed, sets).groupBy("band", "slice", "block").applyInArrow(lambda t: missing_links(t, similar), "a long, b long")
    more = staged(within.distinct(), "others")
    discard(members, stars, named, told, mixed)
    if not more.isEmpty():
        labels = connect(links.union(more))
    return spread_join(rows, staged(labels, "labels"), "node", "left").select("doc_id", "text_hash", F.coalesce("label", "node").alias("component"))


def one_of_each(docs: DataFrame, similar: float = SIMILAR) -> DataFrame:
    """The documents without all but one of each group: the smallest doc_id (nulls last), then the smallest text hash stays."""
    return least_of_each(docs, groups(docs, similar))
