"""Operator 4: toxicity by FTRL-proximal logistic regression.

A text's words, word pairs, triples and skip-grams (one or two words left out) are hashed into 2**`bits` features,
present or absent. FTRL-proximal with rates per coordinate and L1 learns from labelled rows of the learning fold, at
most `most_rows` of them (the smallest by hash of doc_id), in a few passes on the driver; its few non-zero weights
are broadcast and score every whole text in numpy.

Edge cases: null and empty texts get the score of the bias alone; without labels of both kinds that is one half of
the prior; repeated rows are scored each; texts of any length are used whole.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out, ship, text_slices

BITS = 20
MOST_ROWS = 10_000
WORD = re.compile(r"[^\W_]+")
_hashes: dict[str, int] = {}


def word_hashes(words: list[str]) -> np.ndarray:
    from xxhash import xxh3_64_intdigest

    if len(_hashes) > 300_000:
        _hashes.clear()
    for w in words:
        if w not in _hashes:
            _hashes[w] = xxh3_64_intdigest(w)
    return np.fromiter(map(_hashes.__getitem__, words), np.uint64, len(words))


def features(text: str | None, bits: int = BITS) -> np.ndarray:
    """Feature numbers of a text, with repeats."""
    words = WORD.findall((text or "").lower())
    if not words:
        return np.zeros(0, np.int64)
    h = word_hashes(words)
    a, b, c = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9))
    grams = [h, h[:-1] * a + h[1:] * b, h[:-2] * a + h[1:-1] * b + h[2:] * c, h[:-2] * b + h[2:] * c + a, h[:-3] * c + h[3:] * a + b]
    mixed = np.concatenate(grams)
    mixed ^= mixed >> np.uint64(32)
    return ((mixed * a) >> np.uint64(64 - bits)).astype(np.int64)


@dataclass(frozen=True)
class SparseModel:
    """Non-zero weights by feature number."""

    bits: int
    bias: float
    at: np.ndarray
    weight: np.ndarray

    def margin(self, dense: np.ndarray, at: np.ndarray) -> float:
        """Bias and weights of the distinct features at hand."""
        return self.bias + float(dense[np.unique(at[dense[at] != 0])].sum(dtype=np.float64))

    def dense(self) -> np.ndarray:
        out = np.zeros(1 << self.bits, np.float32)
        out[self.at] = self.weight
        return out


def sigmoid(x: float) -> float:
    return float(1 / (1 + np.exp(-np.clip(x, -35, 35))))


class Ftrl:
    """Follow the regularised leader, proximal: a rate for each coordinate, L1 for sparsity."""

    def __init__(self, bits: int = BITS, alpha: float = 1.0, beta: float = 1.0, l1: float = 8.0, l2: float = 0.5):
        self.bits, self.alpha, self.beta, self.l1, self.l2 = bits, alpha, beta, l1, l2
        self.z, self.n = np.zeros((1 << bits) + 1), np.zeros((1 << bits) + 1)

    def weights(self, at: np.ndarray) -> np.ndarray:
        z, bias = self.z[at], at == 1 << self.bits
        l1 = np.where(bias, 0, self.l1)
        w = -(z - np.sign(z) * l1) / ((self.beta + np.sqrt(self.n[at])) / self.alpha + np.where(bias, 0, self.l2))
        return np.where(np.abs(z) > l1, w, 0.0)

    def step(self, at: np.ndarray, y: float) -> None:
        at = np.append(at, np.int32(1 << self.bits))
        w = self.weights(at)
        g = sigmoid(w.sum()) - y
        sigma = (np.sqrt(self.n[at] + g * g) - np.sqrt(self.n[at])) / self.alpha
        self.z[at] += g - sigma * w
        self.n[at] += g * g

    def model(self) -> SparseModel:
        w = self.weights(np.arange((1 << self.bits) + 1))
        at = np.flatnonzero(w[:-1])
        return SparseModel(self.bits, float(w[-1]), at, w[at].astype(np.float32))


def train(rows: Iterable[tuple[np.ndarray, int]], passes: int = 4, seed: int = 11, **options) -> SparseModel:
    """Learn from (distinct features, label) rows in a shuffled order.

    Rows of equal features count once, with the label of most of them; which features get weights is left to L1.
    """
    from xxhash import xxh3_128_digest

    learner, order = Ftrl(**options), np.random.default_rng(seed)
    votes: dict[bytes, list[int]] = {}
    first: list[tuple[bytes, np.ndarray]] = []
    for at, y in rows:
        key = xxh3_128_digest(at.tobytes())
        if key not in votes:
            votes[key] = [0, 0]
            first.append((key, at))
        votes[key][int(y)] += 1
    kept = [(at, int(votes[key][1] > votes[key][0])) for key, at in first]
    first.clear()
    for _ in range(passes):
        for i in order.permutation(len(kept)):
            learner.step(*kept[i])
    return learner.model()


def fit(docs: DataFrame, labels: DataFrame, most_rows: int = MOST_ROWS) -> SparseModel:
    """Learn from labels (doc_id, toxic 0 or 1) of the learning fold, at most `most_rows` rows."""
    ship(docs.sparkSession)
    known = labels.where("doc_id is not null and toxic is not null").where(~held_out("doc_id")).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    sample = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most_rows)
    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(sample), "doc_id")

    def hashed(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in (p for b in batches for p in text_slices(b)):
            lists = [np.unique(features(t)).astype("<i4").tobytes() for t in part.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("toxic"), pa.array(lists, pa.binary())], ["doc_id", "toxic", "at"])

    # one row an id, so the sample's bound holds whatever is repeated; the columns stay Arrow buffers
    rows = chosen.mapInArrow(hashed, "doc_id long, toxic int, at binary").groupBy("doc_id", "toxic").agg(F.min("at").alias("at")).orderBy("doc_id").toArrow()
    return train((np.frombuffer(at.as_buffer(), "<i4"), y) for at, y in zip(rows.column("at"), rows.column("toxic").to_pylist(), strict=True))


def score(docs: DataFrame, model: SparseModel) -> DataFrame:
    """doc_id and score for every document."""
    ship(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = sent.value
        dense = model.dense()
        for part in (p for b in batches for p in text_slices(b)):
            scores = [sigmoid(model.margin(dense, features(t, model.bits))) for t in part.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(scores, pa.float64())], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, score double")
