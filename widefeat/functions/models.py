"""The functions behind arrow and gpu features, row-wise and vectorised; small models that need no files."""

from __future__ import annotations

import base64
import hashlib
import math
import re
import zlib
from collections.abc import Callable, Sequence
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd

from ..model import PlanningError


@dataclass(frozen=True)
class Model:
    """one: a row; many: whole series. Both give the same values."""

    name: str
    one: Callable
    many: Callable[..., pd.Series]


def sigmoid(z: float) -> float:
    return 1.0 / (1.0 + math.exp(-max(-500.0, min(500.0, z))))


# Fixed weights of the quality score: length, words, repetition, digits.
QUALITY = (-1.0, 0.002, 3.0, -2.0, -8.0)


def quality_one(char_len, word_count, ngram_rep, digit_ratio):
    if char_len is None or word_count is None or ngram_rep is None or digit_ratio is None:
        return None
    b, w1, w2, w3, w4 = QUALITY
    return sigmoid(b + w1 * min(word_count, 1000) + w2 * (char_len > 300) + w3 * ngram_rep + w4 * digit_ratio)


def quality_many(char_len, word_count, ngram_rep, digit_ratio):
    b, w1, w2, w3, w4 = QUALITY
    z = b + w1 * np.minimum(word_count.astype(float), 1000) + w2 * (char_len > 300) + w3 * ngram_rep + w4 * digit_ratio
    out = 1.0 / (1.0 + np.exp(-np.clip(z, -500, 500)))
    return out.where(~(char_len.isna() | word_count.isna() | ngram_rep.isna() | digit_ratio.isna()), None)


# Fixed values of the recall classifier: noise of hashed weights, bonus of grams with numerals or operators, scale, bias.
MATH = (0.5, 1.5, 8.0, -1.0)
MATH_SIGNS = re.compile(r"[0-9+=<>/^%]")
BLANKS = re.compile(r"[ \t\n\r\f]+")
_math_words: dict[str, tuple[bytes, bool, float]] = {}


def hashed_weight(gram: bytes, signed: bool) -> float:
    """A gram's weight in the linear classifier: seeded by its hash, more for numerals and operators."""
    noise, bonus, _, _ = MATH
    a, b = hashlib.md5(gram).digest()[:2]
    return (((a << 8) + b) / 65536 - 0.5) * noise + (bonus if signed else 0.0)


def math_weight(gram: str) -> float:
    return hashed_weight(gram.encode(), bool(MATH_SIGNS.search(gram)))


def math_word(word: str) -> tuple[bytes, bool, float]:
    """A word's bytes, whether it has a sign, and its weight; kept, as words are few beside their pairs."""
    found = _math_words.get(word)
    if found is None:
        if len(_math_words) > 500_000:
            _math_words.clear()
        raw, signed = word.encode(), bool(MATH_SIGNS.search(word))
        found = _math_words[word] = (raw, signed, hashed_weight(raw, signed))
    return found


def math_one(plain, quality):
    """A linear classifier over hashed word n-grams (one and two words), scaled by quality."""
    if plain is None or quality is None:
        return None
    words = [math_word(w) for w in BLANKS.split(plain.lower()) if w]
    md5, (noise, bonus, _, _) = hashlib.md5, MATH
    weights = [w for _, _, w in words]
    for (a, x, _), (b, y, _) in zip(words, words[1:], strict=False):  # a blank is no sign: a pair has one if a word has
        h = md5(a + b" " + b).digest()
        weights.append((((h[0] << 8) + h[1]) / 65536 - 0.5) * noise + (bonus if x or y else 0.0))
    mean = sum(weights) / len(weights) if weights else 0.0
    return sigmoid(MATH[2] * mean + MATH[3]) * quality > 0.3


def math_many(plain, quality):
    return pd.Series([math_one(p, None if pd.isna(q) else q) for p, q in zip(plain, quality, strict=True)], dtype="object")


# ---- a safety score, learned

SAFETY_BITS, SAFETY_ROWS = 13, 4000
WORD = re.compile(r"[^\W_]+")


def safety_features(text: str) -> np.ndarray:
    """Buckets of the distinct words of a text, and the bias."""
    found = np.fromiter((zlib.crc32(w.encode()) for w in WORD.findall(text.lower())), np.int64) & ((1 << SAFETY_BITS) - 1)
    return np.append(np.unique(found), 1 << SAFETY_BITS)


def safety_margin(w: np.ndarray, at: np.ndarray) -> float:
    """Features have length one together, so long texts aren't louder than short ones."""
    return float(w[at].sum() / np.sqrt(len(at)))


def train_safety(texts: Sequence[str], toxic: Sequence[int], passes: int = 6, rate: float = 0.2, l2: float = 1e-4, seed: int = 3) -> str:
    """Weights (base64) of a logistic regression by AdaGrad over hashed words; at most SAFETY_ROWS rows are meant."""
    rows = [(safety_features(t or ""), int(y)) for t, y in zip(texts, toxic, strict=True)]
    w, g2 = np.zeros((1 << SAFETY_BITS) + 1), np.full((1 << SAFETY_BITS) + 1, 1e-8)
    rnd = np.random.default_rng(seed)
    for _ in range(passes):
        for i in rnd.permutation(len(rows)):
            at, y = rows[i]
            g = (sigmoid(safety_margin(w, at)) - y) / np.sqrt(len(at)) + l2 * w[at]
            g2[at] += g * g
            w[at] -= rate * g / np.sqrt(g2[at])
    return base64.b64encode(zlib.compress(w.astype(np.float16).tobytes())).decode()


@lru_cache(maxsize=4)
def safety_weights(text: str) -> np.ndarray:
    return np.frombuffer(zlib.decompress(base64.b64decode(text)), np.float16).astype(np.float64)


def safety_with(weights: str) -> Model:
    """The score under some weights: 0 is safe, 1 is not."""

    def one(text):
        if text is None:
            return None
        return sigmoid(safety_margin(safety_weights(weights), safety_features(text)))

    return Model("safety", one, each(one))


def domain_one(text):
    if text is None:
        return None
    return ("long" if len(text) > 2000 else "short") + ("-marked" if "!" in text or "?" in text else "")


def each(one: Callable) -> Callable[..., pd.Series]:
    return lambda *s: pd.Series([one(*(None if v is None or (isinstance(v, float) and v != v) else v for v in vs)) for vs in zip(*s, strict=True)], dtype="object")


@lru_cache(maxsize=1)
def embedding_weights(mb: int = 350) -> np.ndarray:
    """Weights that a worker process loads once: this many MB of them."""
    return np.ones(mb << 17)


def embedding_rows(codes: np.ndarray) -> np.ndarray:
    """A letter's eight weights, those at its code times 1 to 8, around the end of the weights."""
    return embedding_weights().take(codes[:, None].astype(np.int64) * np.arange(1, 9), mode="wrap")


@lru_cache(maxsize=1)
def embedding_table() -> np.ndarray:
    """The rows of the codes below 2048, which most texts keep to."""
    return embedding_rows(np.arange(2048))


def embedding_many(plain):
    """The norm of a text's letters, each drawn from the weights eight times; a whole batch is in memory at once."""
    table = embedding_table()
    codes = [np.frombuffer((t or "").encode("utf-32-le"), "<u4") for t in plain]
    rows = [table.take(c, axis=0) if c.max(initial=0) < len(table) else embedding_rows(c) for c in codes]
    return pd.Series([float(np.sqrt(np.einsum("ij,ij->", r, r))) for r in rows], dtype=float)


def embedding_one(plain):
    return float(embedding_many(pd.Series([plain])).iloc[0])


MODELS = {m.name: m for m in (
    Model("quality", quality_one, quality_many), Model("math_hit", math_one, math_many), Model("domain_model", domain_one, each(domain_one)),
    Model("embedding_norm", embedding_one, embedding_many),
)}


def unload() -> None:
    """Forget what this process has loaded."""
    for held in (embedding_weights, embedding_table, safety_weights):
        held.cache_clear()
    _math_words.clear()


def model_of(spec) -> Model:
    """The functions of a model feature; `safety` brings its weights as a hint."""
    if spec.fn == "safety":
        weights = dict(spec.hints).get("weights")
        if not weights:
            raise PlanningError("safety has no weights: train them with models.train_safety")
        return safety_with(weights)
    return MODELS[spec.fn]
