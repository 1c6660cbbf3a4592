"""Operator 7: the languages of a text as a mixture, by expectation-maximisation.

Letters and blanks of a text give character trigrams, hashed into `buckets`. Their counts by language over all texts
of the learning fold (summed per partition, then by key) give smoothed likelihoods, a table of bounded size that is
broadcast. A text's shares of the languages are found by EM; then the set of languages is chosen by likelihood less a
penalty for each further language, beginning with the single best. The prediction is the set's largest share, the
score that share. A filter on languages keeps the texts of which enough is in languages that are wanted.

Edge cases: texts that are null or have no letter are `und` with score 0, and so are all if nothing can be learned (the
filter then keeps texts with a letter); ties go to the language first in order; whole texts of any length are used, long
ones as bucket counts. The model takes 128 KB a language; beyond MOST_LANGUAGES distinct values of `lang`, which then
are no languages, learning raises an error rather than leave some out.
"""

from __future__ import annotations

from collections.abc import Collection, Iterable, Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, held_out, ship, staged, text_slices

BUCKETS = 1 << 15
MOST_LANGUAGES = 4000
WANTED_SHARE = 0.5
UNDETERMINED = "und"
PREDICTED = "doc_id long, lang_pred string, score double, languages array<struct<lang:string,share:double>>"


@lru_cache(maxsize=1)
def letter_table() -> np.ndarray:
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)


def trigrams(text: str, buckets: int = BUCKETS) -> np.ndarray:
    """Bucket of each trigram over lower-case letters and single blanks; none if there is no letter."""
    points = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), dtype="<u4")
    letters = letter_table()[points]
    if not letters.any():
        return np.zeros(0, np.int64)
    kept = np.where(letters, points, np.uint32(32))
    kept = np.concatenate([[np.uint32(32)], kept, [np.uint32(32)]])
    kept = kept[np.concatenate([[True], (kept[1:] != 32) | (kept[:-1] != 32)])].astype(np.uint64)
    mixed = kept[:-2] * np.uint64(0x9E3779B97F4A7C15) + kept[1:-1] * np.uint64(0xC2B2AE3D27D4EB4F) + kept[2:] * np.uint64(0x165667B19E3779F9)
    return ((mixed ^ (mixed >> np.uint64(31))) * np.uint64(0xD6E8FEB86659FD93) >> np.uint64(40)).astype(np.int64) % buckets


@dataclass(frozen=True)
class MixtureModel:
    """Likelihoods by language (rows) and bucket."""

    languages: tuple[str, ...]
    likelihood: np.ndarray
    rounds: int = 12
    least_share: float = 0.04
    penalty: float = 6.0

    def shares(self, chances: np.ndarray, weights: np.ndarray) -> tuple[np.ndarray, float]:
        """EM for the mixture of the given rows; the shares and the log-likelihood."""
        pi = np.full(len(chances), 1 / len(chances))
        total = weights.sum()
        for _ in range(self.rounds if len(chances) > 1 else 0):
            joint = pi[:, None] * chances
            pi = (joint / joint.sum(axis=0) * weights).sum(axis=1) / total
        return pi, float(np.log(pi @ chances) @ weights)

    def predict(self, text: str | None) -> tuple[str, float, list[tuple[str, float]]]:
        return self.analyse(text)[:3]

    def analyse(self, text: str | None, weigh: bool = False) -> tuple[str, float, list[tuple[str, float]], float]:
        """The prediction, its share, the languages with their shares, and (if `weigh`) how much of the text these explain better than chance."""
        grams = trigrams(text) if text and self.languages else ()
        if not len(grams):
            return UNDETERMINED, 0.0, [], 0.0
        if len(grams) > 4096:
            counts = np.bincount(grams, minlength=self.likelihood.shape[1])
            grams = np.flatnonzero(counts)
            weights = counts[grams].astype(np.float64)
        else:
            weights = np.ones(len(grams))
        chances = self.likelihood[:, grams].astype(np.float64)
        single = np.log(chances) @ weights
        chosen = [int(np.argmax(single))]
        share, best = np.ones(1), float(single[chosen[0]])
        if len(self.languages) > 1:
            mixed, _ = self.shares(chances, weights)
            # trigrams overlap, so each letter counts three times in the likelihood
            cost = self.penalty * np.log(weights.sum() + 1)
            for k in (int(k) for k in np.argsort(-mixed, kind="stable") if mixed[k] >= self.least_share):
                if k not in chosen:
                    tried, gain = self.shares(chances[[*chosen, k]], weights)
                    if gain - best > cost:
                        chosen, share, best = [*chosen, k], tried, gain
        order = sorted(range(len(chosen)), key=lambda i: (-share[i], chosen[i]))
        found = [(self.languages[chosen[i]], float(share[i])) for i in order]
        if not weigh:
            return found[0][0], min(1.0, found[0][1]), found, 1.0
        chance = np.full((1, len(grams)), 1 / self.likelihood.shape[1])
        explained = 1 - float(self.shares(np.concatenate([(share @ chances[chosen])[None], chance]), weights)[0][1])
        return found[0][0], min(1.0, found[0][1]), found, explained


def fit(docs: DataFrame, buckets: int = BUCKETS, smoothing: float = 0.5, most_languages: int = MOST_LANGUAGES) -> MixtureModel:
    """Counts over all texts of the learning fold with a language, for every one of the languages."""
    ship(docs.sparkSession)
    known = docs.where("lang is not null and text is not null").where(~held_out("doc_id")).select(F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))

    def count(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        for part in (p for b in batches for p in text_slices(b)):
            for lang, text in zip(part.column("lang").to_pylist(), part.column("text").to_pylist(), strict=True):
                sums.setdefault(lang, np.zeros(buckets, np.int64))
                sums[lang] += np.bincount(trigrams(text, buckets), minlength=buckets)
        for lang, row in sums.items():
            at = np.flatnonzero(row)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at), pa.array(row[at])], ["lang", "bucket", "n"])

    counts = known.mapInArrow(count, "lang string, bucket long, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n"))
    by_lang = staged(counts.groupBy("lang").agg(F.collect_list(F.struct("bucket", "n")).alias("cells")), "languages")  # at most `buckets` cells each
    names = sorted(r.lang for r in by_lang.select("lang").limit(most_languages + 1).collect())
    if len(names) > most_languages:
        raise ValueError(f"more than {most_languages} distinct values of lang: these are no languages")
    table = np.full((len(names), buckets), smoothing, np.float32)
    for r in by_lang.toLocalIterator():
        table[names.index(r.lang), [c.bucket for c in r.cells]] += [c.n for c in r.cells]
    discard(by_lang)
    return MixtureModel(tuple(names), table / table.sum(axis=1, keepdims=True, dtype=np.float64).astype(np.float32))


def identify(docs: DataFrame, model: MixtureModel) -> DataFrame:
    """doc_id, lang_pred, score and the languages with their shares, for every document."""
    spark = docs.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast(model)
    kind = pa.list_(pa.struct([("lang", pa.string()), ("share", pa.float64())]))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in (p for b in batches for p in text_slices(b)):
            found = [sent.value.predict(t) for t in part.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [part.column("doc_id"), pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64()), pa.array([[{"lang": a, "share": b} for a, b in f[2]] for f in found], kind)],
                ["doc_id", "lang_pred", "score", "languages"],
            )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, PREDICTED)


def keep(docs: DataFrame, model: MixtureModel, wanted: Collection[str] | None = None, share: float = WANTED_SHARE) -> DataFrame:
    """The rows of `docs` (any columns, text among them) of which a `share` or more is in `wanted` languages.

    By default all learned languages are wanted. EM weighs the languages found against trigrams at random, so what is in
    no language (codes, keys, noise, other scripts) counts for none; the shares in wanted languages add up. An unknown
    language that shares most trigrams with a learned one passes as that.
    """
    spark = docs.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast(model)
    accepted = frozenset(model.languages if wanted is None else wanted)

    def stays(text: str | None) -> bool:
        if not sent.value.languages:
            return bool(text) and len(trigrams(text)) > 0
        _, _, found, explained = sent.value.analyse(text, weigh=True)
        return explained * sum(s for x, s in found if x in accepted) >= share

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in (p for b in batches for p in text_slices(b)):
            yield part.filter(pa.array([stays(t) for t in part.column("text").to_pylist()], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
