"""Operator 2: BPE encoding and decoding with a minimal acyclic transducer as lexicon.

The corpus's most frequent words (counted over all documents) are compiled into a minimal acyclic automaton whose
arcs carry numbers: along a word's path they add up to its place in a table of id outputs, so words share prefixes
and suffixes. The automaton is laid out as flat arrays in one file of bounded size (`most_words`), broadcast,
memory-mapped once per machine and walked by numpy for all new words of a batch at once. Words it lacks are merged
exactly, pair by pair in rank order. Decoding looks tokens up by id and joins them as the tokenizers library does.

Edge cases: null text counts as empty; unusual characters and special tokens are normalised and split by the
library's own components; empty tables give an empty lexicon; repeated rows are encoded each.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import mmap
import os
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import local_scratch, ship, staged, text_slices
from .tokens import WordCounts, WordEncoder, tokenizer_path

MOST_WORDS = 50_000
DIGEST = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


# ---- exact merges


def byte_alphabet() -> list[str]:
    """The printable stand-in of each byte, as byte-level vocabularies spell them."""
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    shifted = iter(range(256, 512))
    return [chr(b) if b in printable else chr(next(shifted)) for b in range(256)]


class ExactMerger:
    """BPE of one pre-token: the lowest-ranked adjacent pair is merged first, the leftmost of equals."""

    LONG, NONE = 32, (1 << 62, 0)

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        vocab, suffix = model["vocab"], model["end_of_word_suffix"] or ""
        alphabet = byte_alphabet()
        self.inner = [vocab[c] for c in alphabet]
        self.last = [vocab[c + suffix] for c in alphabet]
        self.ranks: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, (a, b) in enumerate(model["merges"]):
            self.ranks.setdefault((vocab[a], vocab[b]), (rank, vocab[a + b]))
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.tokens = {i: t for t, i in vocab.items()} | {i: t for t, i in self.special.items()}

    def merge(self, word: bytes) -> list[int]:
        if not word:
            return []
        ids = [self.inner[b] for b in word]
        ids[-1] = self.last[word[-1]]
        return self._short(ids) if len(ids) <= self.LONG else self._long(ids)

    def _short(self, ids: list[int]) -> list[int]:
        get, none = self.ranks.get, self.NONE
        pairs = [get(p, none) for p in zip(ids, ids[1:], strict=False)]
        while pairs and (best := min(pairs)) is not none:
            i, merged = pairs.index(best), best[1]
            ids[i : i + 2] = [merged]
            del pairs[i]
            if i:
                pairs[i - 1] = get((ids[i - 1], merged), none)
            if i < len(pairs):
                pairs[i] = get((merged, ids[i + 1]), none)
        return ids

    def _long(self, ids: list[int]) -> list[int]:
        """The same in n log n, with a heap over a linked list."""
        n, ranks = len(ids), self.ranks
        after, before = [*range(1, n), -1], [-1, *range(n - 1)]
        heap: list[tuple[int, int, int, int, int]] = []

        def offer(i: int) -> None:
            if i >= 0 and after[i] >= 0 and (r := ranks.get((ids[i], ids[after[i]]))):
                heapq.heappush(heap, (r[0], i, r[1], ids[i], ids[after[i]]))

        for i in range(n):
            offer(i)
        while heap:
            _, i, merged, a, b = heapq.heappop(heap)
            j = after[i]
            if ids[i] != a or j < 0 or ids[j] != b:
                continue
            ids[i], ids[j], after[i] = merged, -1, after[j]
            if after[j] >= 0:
                before[after[j]] = i
            offer(before[i])
            offer(i)
        return [x for x in ids if x >= 0]


# ---- the automaton


def minimal_automaton(words: list[bytes]) -> tuple[list[dict[int, int]], list[bool]]:
    """States' arcs and acceptance of the minimal acyclic automaton of sorted distinct words; state 0 is the root."""
    arcs: list[dict[int, int]] = [{}]
    accepts = [False]
    register: dict[tuple, int] = {}
    path: list[tuple[int, int, int]] = []  # (state, label, child) of the last word
    free: list[int] = []

    def close(down_to: int) -> None:
        while len(path) > down_to:
            state, label, child = path.pop()
            key = (accepts[child], *arcs[child].items())
            if (same := register.setdefault(key, child)) != child:
                arcs[state][label] = same
                free.append(child)

    previous = b""
    for word in words:
        shared = len(os.path.commonprefix([previous, word]))
        close(shared)
        state = path[-1][2] if path else 0
        for b in word[shared:]:
            if free:
                child = free.pop()
                arcs[child], accepts[child] = {}, False
            else:
                child = len(arcs)
                arcs.append({})
                accepts.append(False)
            arcs[state][b] = child
            path.append((state, b, child))
            state = child
        accepts[state] = True
        previous = word
    close(0)
    return arcs, accepts


@dataclass
class Lexicon:
    """Flat arrays of the transducer: arcs sorted by (state, label) with target and output, and the words' ids."""

    arc_key: np.ndarray
    arc_target: np.ndarray
    arc_output: np.ndarray
    accepts: np.ndarray
    ids_start: np.ndarray
    ids: np.ndarray

    FIELDS = (("arc_key", "<i8"), ("arc_target", "<i4"), ("arc_output", "<i4"), ("accepts", "u1"), ("ids_start", "<i4"), ("ids", "<u4"))

    @classmethod
    def compile(cls, outputs: dict[bytes, list[int]]) -> Lexicon:
        words = sorted(w for w in outputs if w)
        arcs, accepts = minimal_automaton(words)
        below: dict[int, int] = {}  # words from a state on
        order, stack = [], [0]
        seen = {0}
        while stack:
            s = stack.pop()
            order.append(s)
            for t in arcs[s].values():
                if t not in seen:
                    seen.add(t)
                    stack.append(t)

        def count(root: int) -> None:
            todo = [(root, False)]
            while todo:
                s, ready = todo.pop()
                if s in below:
                    continue
                if ready:
                    below[s] = accepts[s] + sum(below[t] for t in arcs[s].values())
                else:
                    todo.append((s, True))
                    todo += [(t, False) for t in arcs[s].values() if t not in below]

        count(0)
        number = {s: i for i, s in enumerate(order)}
        rows = []
        for s in order:
            output = int(accepts[s])
            for label, t in sorted(arcs[s].items()):
                rows.append((number[s] << 8 | label, number[t], output))
                output += below[t]
        table = np.asarray(sorted(rows) or np.zeros((0, 3)), dtype=np.int64).reshape(-1, 3)
        lists = [outputs[w] for w in words]
        starts = np.zeros(len(lists) + 1, dtype=np.int64)
        np.cumsum([len(x) for x in lists], out=starts[1:])
        return cls(*table.T, np.asarray([accepts[s] for s in order]), starts, np.asarray([i for x in lists for i in x]))

    def to_bytes(self) -> bytes:
        parts = [np.ascontiguousarray(getattr(self, n), dtype=t) for n, t in self.FIELDS]
        head = np.asarray([len(p) for p in parts], dtype="<i8").tobytes()
        return head + b"".join(p.tobytes() + b"\0" * (-p.nbytes % 8) for p in parts)

    @classmethod
    def of_buffer(cls, buffer) -> Lexicon:
        sizes, at, parts = np.frombuffer(buffer, "<i8", len(cls.FIELDS)), 8 * len(cls.FIELDS), []
        for (_, t), n in zip(cls.FIELDS, sizes.tolist(), strict=True):
            parts.append(np.frombuffer(buffer, t, n, at))
            at += parts[-1].nbytes + -parts[-1].nbytes % 8
        return cls(*parts)

    @classmethod
    def mapped(cls, blob: bytes) -> Lexicon:
        """From this machine's memory-mapped copy of `blob`, written once under a name made of its content."""
        path = os.path.join(local_scratch(), f"lexicon-{hashlib.sha256(blob).hexdigest()[:20]}.bin")
        if not os.path.exists(path):
            own = f"{path}.{os.getpid()}"
            with open(own, "wb") as f:
                f.write(blob)
            os.replace(own, path)
        with open(path, "rb") as f:
            return cls.of_buffer(mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ))

    def find(self, words: list[bytes]) -> np.ndarray:
        """Each word's number, -1 if it isn't in the lexicon; all words step through the automaton together."""
        n = len(words)
        sizes = np.fromiter(map(len, words), dtype=np.int64, count=n)
        starts = np.cumsum(sizes) - sizes
        letters = np.frombuffer(b"".join(words), dtype=np.uint8)
        state, number, alive = np.zeros(n, np.int64), np.zeros(n, np.int64), np.flatnonzero(sizes > 0)
        result = np.full(n, -1, np.int64)
        step = 0
        while len(alive) and len(self.arc_key):
            key = state[alive] << 8 | letters[starts[alive] + step]
            at = np.searchsorted(self.arc_key, key)
            at[at == len(self.arc_key)] = 0
            alive, at = (x[self.arc_key[at] == key] for x in (alive, at))
            state[alive] = self.arc_target[at]
            number[alive] += self.arc_output[at]
            step += 1
            done = alive[sizes[alive] == step]
            done = done[self.accepts[state[done]] == 1]
            result[done] = number[done]
            alive = alive[sizes[alive] > step]
        return result


# ---- encoding and decoding


class TransducerCodec:
    """Exact encoding and decoding with a lexicon and, for what it lacks, merges."""

    def __init__(self, path: str, lexicon: Lexicon | None = None):
        from tokenizers import Tokenizer

        self.merger, self.lexicon = ExactMerger(path), lexicon
        self.library = Tokenizer.from_file(path)
        self.encoder = WordEncoder(self.encode_words, self.encode_chunks)
        self.spelled = [self.merger.tokens.get(i, "") for i in range(max(self.merger.tokens) + 1)]

    def encode_raw(self, chunk: str) -> list[int]:
        """A chunk with special tokens or unusual characters."""
        ids: list[int] = []
        while chunk:
            found = min(((at, -len(s), s) for s in self.merger.special if (at := chunk.find(s)) >= 0), default=None)
            head, chunk, special = (chunk, "", None) if found is None else (chunk[: found[0]], chunk[found[0] + len(found[2]) :], found[2])
            if head:
                back = {c: b for b, c in enumerate(byte_alphabet())}
                for piece, _ in self.library.pre_tokenizer.pre_tokenize_str(self.library.normalizer.normalize_str(head)):
                    ids += self.merger.merge(bytes(back[c] for c in piece))
            if special is not None:
                ids.append(self.merger.special[special])
        return ids

    def encode_chunks(self, chunks: list[str]) -> list[bytes]:
        return [np.asarray(self.encode_raw(c), dtype="<u4").tobytes() for c in chunks]

    def encode_words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        letters = [w.encode() for w in words]
        numbers = self.lexicon.find(letters) if self.lexicon is not None else np.full(len(words), -1)
        found = np.flatnonzero(numbers >= 0)
        merged = {i: self.merger.merge(letters[i]) for i in np.flatnonzero(numbers < 0).tolist()}
        sizes = np.zeros(len(words), np.int64)
        sizes[list(merged)] = [len(x) for x in merged.values()]
        if len(found):
            first = self.lexicon.ids_start[numbers[found]].astype(np.int64)
            sizes[found] = self.lexicon.ids_start[numbers[found] + 1] - first
        ids, starts = np.zeros(sizes.sum(), np.uint32), np.cumsum(sizes) - sizes
        for at, many, source in ((found, self.lexicon, None), (np.asarray(list(merged), np.int64), None, merged)):
            if len(at):
                n = sizes[at]
                within = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                values = many.ids[np.repeat(first, n) + within] if source is None else np.fromiter((i for x in source.values() for i in x), np.uint32, n.sum())
                ids[np.repeat(starts[at], n) + within] = values
        return ids, sizes

    def encode(self, texts: list[str | None]) -> list[bytes]:
        return self.encoder.encode(texts)

    def decode(self, ids: Iterable[int]) -> str:
        return " ".join(map(self.spelled.__getitem__, ids))


def count_words(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Words and how often this partition has them; counts are handed on when there are many."""
    counts = WordCounts()
    for part in (p for b in batches for p in text_slices(b)):
        counts.add(part.column("text").to_pylist())
        if len(counts.words) > 300_000:
            yield pa.RecordBatch.from_arrays([pa.array(counts.words, pa.string()), pa.array(counts.counts)], ["word", "n"])
            counts = WordCounts()
    yield pa.RecordBatch.from_arrays([pa.array(counts.words, pa.string()), pa.array(counts.counts)], ["word", "n"])


def frequent_words(docs: DataFrame, most_words: int = MOST_WORDS) -> list[str]:
    """The `most_words` most frequent words of all documents (all, if fewer); ties go by hash, then by word.

    Counts are dealt into bands of some six percent, each cut into 256 parts by the words' hashes; a histogram of these
    cells, of bounded size, tells up to which cell all words fit, and only those and the next cell's least come to the driver.
    """
    ship(docs.sparkSession)
    found = docs.select(F.col("text").cast("string").alias("text")).mapInArrow(count_words, "word string, n long")
    cell = (-F.floor(F.log("n") * 16) * 256 + F.pmod(F.xxhash64("word"), F.lit(256))).cast("int")
    counts = staged(found.groupBy("word").agg(F.sum("n").alias("n")).withColumn("cell", cell), "word-counts")
    total, last = 0, None
    for r in counts.groupBy("cell").agg(F.count("*").alias("words")).orderBy("cell").collect():
        last, total = r.cell, total + r.words
        if total >= most_words:
            break
    if last is None:
        return []
    whole = [r.word for r in counts.where(F.col("cell") < last).select("word").collect()]
    part = counts.where(F.col("cell") == last).orderBy(F.desc("n"), F.xxhash64("word"), "word").limit(most_words - len(whole))
    return sorted(whole + [r.word for r in part.select("word").collect()])


def compile_lexicon(words: Iterable[str], tokenizer: str | None = None) -> Lexicon:
    merger = ExactMerger(tokenizer or tokenizer_path())
    return Lexicon.compile({w.encode(): merger.merge(w.encode()) for w in words})


_kept: dict[tuple[str, int], TransducerCodec] = {}


def kept_codec(path: str, blob) -> TransducerCodec:
    """The codec of a broadcast lexicon, kept for all tasks of a worker process."""
    key = (path, hash(blob.value))
    if key not in _kept:
        _kept.clear()
        _kept[key] = TransducerCodec(path, Lexicon.mapped(blob.value))
    return _kept[key]


def codec_digest(docs: DataFrame, tokenizer: str | None = None, most_words: int = MOST_WORDS) -> DataFrame:
    """Encode and decode every text: doc_id, n_tokens, ids_sha256, decoded_sha256."""
    spark = docs.sparkSession
    path = tokenizer or tokenizer_path()
    blob = spark.sparkContext.broadcast(compile_lexicon(frequent_words(docs, most_words), path).to_bytes())

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = kept_codec(path, blob)
        for part in (p for b in batches for p in text_slices(b)):
            encoded = codec.encode(part.column("text").to_pylist())
            decoded = [codec.decode(np.frombuffer(x, "<u4").tolist()).encode() for x in encoded]
            columns = [pa.array([len(x) // 4 for x in encoded], pa.int64()), *(pa.array([hashlib.sha256(x).hexdigest() for x in xs], pa.string()) for xs in (encoded, decoded))]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), *columns], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, DIGEST)
