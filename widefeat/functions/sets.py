"""Features that need all rows of their inputs: near-duplicate groups over min-hash signatures, perplexity by language.

Shingles of five words, a similarity of 0.8 or more between signatures. Bands of a signature are join keys; each
distinct signature enters once. A band's members that are like its least one are linked to it alone; only the rest is
compared with all members, so a large group of near copies gives a star, not all pairs, and no connection is lost.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import BATCH, ID, KEYS, FeatureSpec, Output

HASHES, BAND, SHINGLE, SIMILAR = 64, 4, 5, 0.8
SLICE = 512
# Fixed multipliers of the hash family, from a rule.
SEEDS = tuple((2 * i + 1) * 0x9E3779B97F4A7C1 % (1 << 61) for i in range(HASHES))


def minhash_feature(text: str = "processed.plain", source: str = "processed") -> FeatureSpec:
    """Sixty-four minima of seeded hashes of word shingles, as array<bigint>."""
    words = f"filter(split(lower({text}), '\\\\s+'), w -> w <> '')"
    shingles = f"transform(sequence(1, greatest(size(_mh_words) - {SHINGLE - 1}, 1)), i -> xxhash64(array_join(slice(_mh_words, i, {SHINGLE}), ' ')))"
    seeds = ", ".join(f"{s}L" for s in SEEDS)
    expr = f"transform(array({seeds}), s -> array_min(transform(_mh_grams, g -> xxhash64(g, s))))"
    return FeatureSpec("minhash", (source,), (Output("minhash_sig", "array<bigint>"),), (expr,), lets=(("_mh_words", words), ("_mh_grams", f"array_distinct({shingles})")))


def near_dup_feature() -> FeatureSpec:
    """The least entity_id of each group of near duplicates."""
    return FeatureSpec("near_dup", ("minhash_sig",), (Output("near_dup_group", "string"),), fn="near_dup_group", scope="table")


def near_dup_groups(rows: DataFrame, staged: Callable[[DataFrame, str], DataFrame], out: str = "near_dup_group") -> DataFrame:
    """entity_id, batch_name and group of rows with minhash_sig; `staged` writes a frame and reads it again."""
    distinct = staged(rows.where("minhash_sig is not null").groupBy("minhash_sig").agg(F.min(ID).alias("node")), "signatures")
    bands = F.transform(F.sequence(F.lit(0), F.lit(HASHES // BAND - 1)), lambda b: F.xxhash64(b, F.slice("minhash_sig", b * BAND + 1, BAND)))
    keyed = staged(distinct.select("node", "minhash_sig", F.explode(bands).alias("band")), "bands")
    alike = F.expr(f"aggregate(zip_with(s1, s2, (a, b) -> if(a = b, 1, 0)), 0, (x, y) -> x + y) >= {SIMILAR * HASHES}")
    first = keyed.groupBy("band").agg(F.min(F.struct(F.col("node").alias("a"), F.col("minhash_sig").alias("s1"))).alias("f"), F.count("*").alias("n")).where("n > 1").select("band", "f.*", F.ceil(F.col("n") / SLICE).cast("int").alias("slices"))
    met = staged(keyed.select("band", F.col("node").alias("b"), F.col("minhash_sig").alias("s2")).join(first, "band").where(F.col("a") != F.col("b")).withColumn("alike", alike), "met")
    # members unlike the first meet all others slice by slice, so a crowded band is the work of many tasks
    own = F.pmod(F.xxhash64("b"), F.col("slices")).cast("int").alias("slice")
    rest = met.where(~F.col("alike")).select("band", F.col("b").alias("a"), F.col("s2").alias("s1"), F.explode(F.sequence(F.lit(0), F.col("slices") - 1)).alias("slice"))
    pairs = rest.join(met.select("band", "b", "s2", own), ["band", "slice"]).where(F.col("a") != F.col("b")).where(alike).select("a", "b")
    edges = staged(met.where("alike").select("a", "b").union(pairs).distinct(), "links")
    both = staged(edges.union(edges.select("b", "a")), "both")
    labels = staged(distinct.select("node", F.col("node").alias("label")), "labels")
    while True:
        heard = both.join(labels, F.col("b") == F.col("node")).groupBy("a").agg(F.min("label").alias("heard"))
        moved = staged(labels.join(heard, F.col("node") == F.col("a"), "left").select("node", F.col("label").alias("old"), F.least("label", "heard").alias("label")), "labels")
        labels = moved.select("node", "label")
        if moved.where("old <> label").isEmpty():
            break
    named = distinct.join(labels, "node").select("minhash_sig", "label")
    return rows.join(named, "minhash_sig", "left").select(ID, BATCH, F.col("label").alias(out))


# ---- perplexity under a language model counted over all rows

CELLS = 1 << 16
ADDED, ALPHABET = 0.1, 64


def trigram_cells(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Cells of a text's character trigrams and of their first two characters."""
    c = np.frombuffer(f" {text.lower()} ".encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
    pairs = c[:-2] * np.uint64(0x9E3779B97F4A7C15) + c[1:-1] * np.uint64(0xC2B2AE3D27D4EB4F)
    cell = lambda h: ((h ^ (h >> np.uint64(29))) * np.uint64(0xD6E8FEB86659FD93) >> np.uint64(48)).astype(np.int64)
    return cell(pairs + c[2:] * np.uint64(0x165667B19E3779F9)), cell(pairs)


def perplexity(rows: DataFrame, staged: Callable[[DataFrame, str], DataFrame], out: str = "ppl") -> DataFrame:
    """exp of the mean surprise of each character after the two before it, by counts over all rows of the same language.

    Counts are hashed into CELLS cells a language and summed per partition first; languages are those of lang_guess, a
    handful, so the model that is broadcast has a fixed size. Texts of less than one character have none.
    """
    spark = rows.sparkSession
    texts = rows.select(*KEYS, F.coalesce("lang_guess", F.lit("und")).alias("lang"), F.col("processed.plain").alias("plain"))

    def count(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        for b in batches:
            for lang, text in zip(b.column("lang").to_pylist(), b.column("plain").to_pylist(), strict=True):
                if text:
                    mine = sums.setdefault(lang, np.zeros((2, CELLS), np.int64))
                    for k, cells in enumerate(trigram_cells(text)):
                        np.add.at(mine[k], cells, 1)
        for lang, mine in sums.items():
            k, at = np.nonzero(mine)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(k, pa.int32()), pa.array(at, pa.int32()), pa.array(mine[k, at])], ["lang", "k", "cell", "n"])

    counts = texts.select("lang", "plain").mapInArrow(count, "lang string, k int, cell int, n long").groupBy("lang", "k", "cell").agg(F.sum("n").alias("n"))
    model: dict[str, np.ndarray] = {}
    for r in staged(counts, "trigrams").toLocalIterator():
        model.setdefault(r.lang, np.zeros((2, CELLS)))[r.k, r.cell] = r.n
    sent = spark.sparkContext.broadcast(model)

    def score(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found: list[float | None] = []
            for lang, text in zip(b.column("lang").to_pylist(), b.column("plain").to_pylist(), strict=True):
                if not text:
                    found.append(None)
                    continue
                three, two = trigram_cells(text)
                n = sent.value[lang]
                found.append(float(np.exp(-np.log((n[0, three] + ADDED) / (n[1, two] + ADDED * ALPHABET)).mean())))
            yield pa.RecordBatch.from_arrays([b.column(ID), b.column(BATCH), pa.array(found, pa.float64())], [*KEYS, out])

    return texts.mapInArrow(score, f"{ID} string, {BATCH} string, {out} double")


SETS = {"near_dup_group": near_dup_groups, "ppl": perplexity}
