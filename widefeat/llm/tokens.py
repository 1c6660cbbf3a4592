"""Word-wise encoding with a public word-level BPE file of the tokenizers library.

Ids of a text are the ids of its pre-tokens, one after another, as merges never cross a pre-token. Pre-tokens of a
block of texts are found by numpy, all at once, and looked up by a hash, then compared letter by letter with the word
found; only distinct ones that this worker doesn't know yet are encoded. Known ones are kept in a store of bounded size.
"""

from __future__ import annotations

import os
import re
from collections.abc import Callable, Iterable
from functools import lru_cache
from itertools import chain, repeat

import numpy as np

DEFAULT_TOKENIZER = "word_bpe_49k.json"
BLOCK_CHARS = 400_000

# In the plain range NFC changes nothing and lower-casing has no special case.
PLAIN = r"\t\n\r\x20-\x7e\u00a1-\u00a9\u00ab-\u00b1\u00b4\u00b6-\u00b8\u00bb\u00bf-\u012f\u0131-\u0233"
PLAIN_TEXT = re.compile(f"[{PLAIN}]*")
ODD_CHUNK = re.compile(rf"[^ \t\n\r]*(?:[^{PLAIN}]|<\|)[^ \t\n\r]*")
SPECIAL_MARK = "<|"
# Contractions of the file's pre-token pattern, by their letters.
CONTRACTIONS_1, CONTRACTIONS_2 = "stmd", ("re", "ve", "ll")
BLANK, LETTER, NUMBER, OTHER = range(4)


def tokenizer_path(name: str = DEFAULT_TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def is_plain(text: str) -> bool:
    """Whether lower-casing and character classes alone give the pre-tokens of a text."""
    return SPECIAL_MARK not in text and PLAIN_TEXT.fullmatch(text) is not None


@lru_cache(maxsize=1)
def classes() -> np.ndarray:
    """The class of each code point of the plain range and what it lower-cases to."""
    import unicodedata

    kinds = {"L": LETTER, "N": NUMBER}
    return np.asarray([BLANK if chr(c).isspace() else kinds.get(unicodedata.category(chr(c))[0], OTHER) for c in range(0x300)], dtype=np.uint8)


def find_words(points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the pre-tokens in code points of plain lower-case text that ends with three blanks."""
    kind = classes()[points]
    before = np.concatenate([[np.uint8(BLANK)], kind[:-1]])
    start = (kind != BLANK) & ((kind != before) | (kind == NUMBER))
    quotes = np.flatnonzero((points == 39) & start)
    if len(quotes) and len(points) > 4:
        quotes = quotes[quotes < len(points) - 3]
        one, two = points[quotes + 1], points[quotes + 2]
        short = np.isin(one, [ord(c) for c in CONTRACTIONS_1])
        long = np.zeros(len(quotes), bool)
        for a, b in CONTRACTIONS_2:
            long |= (one == ord(a)) & (two == ord(b))
        for at, size in ((quotes[short], 2), (quotes[long], 3)):
            start[at + 1] = False
            start[at + size] = kind[at + size] != BLANK
    edges = np.flatnonzero(start | ((kind == BLANK) & (before != BLANK)))
    is_start = start[edges]
    return edges[is_start], edges[np.flatnonzero(is_start) + 1]


def hashes_of(letters: np.ndarray, place: np.ndarray, first: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each word: the sum of a mix of each letter with its place in the word."""
    h = letters.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + place.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xA24BAED4963EE407)
    h ^= h >> np.uint64(29)
    return np.add.reduceat(h, first)


class WordTable:
    """Known words by place. Hashes only propose a place; every occurrence is compared letter by letter with the word there."""

    def __init__(self) -> None:
        self.by_hash: dict[int, int] = {}
        self.by_word: dict[str, int] = {}  # words whose hash belongs to another word
        self.letters, self.first, self.sizes = np.zeros(0, np.uint16), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def __len__(self) -> int:
        return len(self.first)

    def find(self, points: np.ndarray, start: np.ndarray, end: np.ndarray, most: int | None = None) -> tuple[np.ndarray, list[str]]:
        """The place of each word, and the words that are new (in order of their places); all is forgotten first if more than `most` would be known."""
        sizes = end - start
        after = np.cumsum(sizes)
        first = after - sizes
        within = np.arange(after[-1]) - np.repeat(first, sizes)
        letters = points[np.repeat(start, sizes) + within].astype(np.uint16)
        distinct, example, inverse = np.unique(hashes_of(letters, within, first), return_index=True, return_inverse=True)
        keys = distinct.tolist()
        places = np.fromiter(map(self.by_hash.get, keys, repeat(-1)), np.int64, len(keys))
        missing = np.flatnonzero(places < 0)
        if most is not None and len(missing) and len(self) + len(missing) > most:
            self.__init__()
            places[:], missing = -1, np.arange(len(keys))
        new: list[str] = []
        if len(missing):
            places[missing] = np.arange(len(self), len(self) + len(missing))
            self.by_hash.update(zip(distinct[missing].tolist(), places[missing].tolist(), strict=True))
            at = example[missing]
            new = self._store(points, start[at], end[at])
        place = places[inverse]
        known = np.minimum(np.repeat(self.first[place], sizes) + within, len(self.letters) - 1)
        wrong = (self.sizes[place] != sizes) | np.logical_or.reduceat(self.letters[known] != letters, first)
        for i in np.flatnonzero(wrong).tolist():
            word = word_at(points, start[i], end[i])
            if word not in self.by_word:
                self.by_word[word] = len(self)
                new += self._store(points, start[i : i + 1], end[i : i + 1])
            place[i] = self.by_word[word]
        return place, new

    def _store(self, points: np.ndarray, start: np.ndarray, end: np.ndarray) -> list[str]:
        """All words at once: their letters are kept, and taken as one text with a blank after each, which no word holds."""
        sizes = end - start
        first = np.cumsum(sizes) - sizes
        of_word = np.repeat(np.arange(len(sizes)), sizes)
        at = np.arange(len(of_word))
        letters = points[at + (start - first)[of_word]]
        spaced = np.full(len(letters) + len(sizes), 32, "<u4")
        spaced[at + of_word] = letters
        self.first = np.concatenate([self.first, len(self.letters) + first])
        self.sizes = np.concatenate([self.sizes, sizes])
        self.letters = np.concatenate([self.letters, letters.astype(np.uint16)])
        return spaced.tobytes().decode("utf-32-le").split(" ")[:-1]


def block_of(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of the lower-cased texts, a blank after each and two more at the end, and where each text ends."""
    points = np.frombuffer((" ".join(texts) + "   ").lower().encode("utf-32-le"), dtype="<u4")
    return points, np.cumsum([len(t) + 1 for t in texts])


def word_at(points: np.ndarray, a: int, b: int) -> str:
    return points[a:b].tobytes().decode("utf-32-le")


def blocks(texts: list[str]) -> Iterable[tuple[int, int]]:
    """Ranges of texts of some BLOCK_CHARS together, one text at least."""
    start = total = 0
    for i, t in enumerate(texts):
        if total and total + len(t) > BLOCK_CHARS:
            yield start, i
            start = i
            total = 0
        total += len(t) + 1
    if start < len(texts):
        yield start, len(texts)


class WordEncoder:
    """Texts to ids (little-endian unsigned 32-bit).

    `encode_words` gets distinct new pre-tokens and returns all their ids and how many each has; `encode_raw` gets
    chunks between blanks with unusual characters or special tokens, which need all of the tokenizer's rules. When a store is full it keeps what the block in hand
    uses and forgets the rest.
    """

    def __init__(self, encode_words: Callable[[list[str]], tuple[np.ndarray, np.ndarray]], encode_raw: Callable[[list[str]], Iterable[bytes]], most: int = 400_000):
        self.encode_words, self.encode_raw, self.most, self.raw = encode_words, encode_raw, most, {}
        self.forget()

    def forget(self) -> None:
        self.words = WordTable()
        self.first_id, self.n_ids, self.ids = (np.zeros(0, t) for t in (np.int64, np.int64, np.uint32))

    def _learn(self, new: list[str]) -> None:
        if len(new) == len(self.words):  # all known ones were forgotten
            self.first_id, self.n_ids, self.ids = (np.zeros(0, t) for t in (np.int64, np.int64, np.uint32))
        ids, sizes = self.encode_words(new)
        self.first_id = np.concatenate([self.first_id, len(self.ids) + np.cumsum(sizes) - sizes])
        self.n_ids = np.concatenate([self.n_ids, sizes])
        self.ids = np.concatenate([self.ids, ids.astype(np.uint32, copy=False)])

    def encode_plain(self, texts: list[str]) -> list[bytes]:
        points, ends = block_of(texts)
        start, end = find_words(points)
        if not len(start):
            return [b""] * len(texts)
        place, new = self.words.find(points, start, end, self.most)
        if new:
            self._learn(new)
        sizes = self.n_ids[place]
        after = np.cumsum(sizes)
        ids = self.ids[np.repeat(self.first_id[place] - (after - sizes), sizes) + np.arange(after[-1])].astype("<u4", copy=False)
        upto = np.searchsorted(start, ends)
        cuts = 4 * np.concatenate([[0], np.concatenate([[0], after])[upto]])
        whole = ids.tobytes()
        return [whole[a:b] for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]

    def _raw(self, chunk: str) -> bytes:
        if (found := self.raw.get(chunk)) is None:
            if len(self.raw) >= self.most // 4:
                self.raw.clear()
            found = self.raw[chunk] = next(iter(self.encode_raw([chunk])))
        return found

    def encode(self, texts: list[str | None]) -> list[bytes]:
        plain: list[str] = []
        order: list[list[int | bytes]] = []  # of each text its parts: places in plain, or ids of odd chunks
        for text in texts:
            parts: list[int | bytes] = []
            order.append(parts)
            if not text:
                continue
            if is_plain(text):
                parts.append(len(plain))
                plain.append(text)
                continue
            at = 0
            for odd in ODD_CHUNK.finditer(text):
                parts += (len(plain), self._raw(odd[0]))
                plain.append(text[at : odd.start()])
                at = odd.end()
            parts.append(len(plain))
            plain.append(text[at:])
        done = [x for a, b in blocks(plain) for x in self.encode_plain(plain[a:b])]
        return [done[p[0]] if len(p) == 1 else b"".join(done[x] if isinstance(x, int) else x for x in p) for p in order]


@lru_cache(maxsize=2)
def library_encoder(path: str) -> WordEncoder:
    """Words and chunks are encoded by the tokenizers library itself; kept for all tasks of a worker process.

    Pre-tokens are handed to the file's BPE model many at a time, a blank between; the last id of each ends a word.
    """
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer, pre_tokenizers

    whole, words_only = Tokenizer.from_file(path), Tokenizer.from_file(path)
    for t in (whole, words_only):
        t.no_truncation()
        t.no_padding()
    words_only.normalizer = None
    words_only.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
    words_only.model._resize_cache(0)
    suffix = whole.model.end_of_word_suffix
    last = np.zeros(whole.get_vocab_size(), bool)
    last[[i for token, i in whole.get_vocab().items() if token.endswith(suffix)]] = True

    def encode_words(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        joined = [" ".join(words[i : i + 200]) for i in range(0, len(words), 200)]
        ids = np.fromiter(chain.from_iterable(x.ids for x in words_only.encode_batch_fast(joined, add_special_tokens=False)), np.uint32)
        return ids, np.diff(np.flatnonzero(last[ids]), prepend=-1)

    def encode_raw(chunks: list[str]) -> list[bytes]:
        return [np.asarray(x.ids, dtype="<u4").tobytes() for x in whole.encode_batch_fast(chunks, add_special_tokens=False)]

    return WordEncoder(encode_words, encode_raw)


class WordCounts:
    """How often each plain pre-token occurs in the texts added."""

    def __init__(self) -> None:
        self.known, self.words, self.counts = WordTable(), [], np.zeros(0, np.int64)

    def add(self, texts: list[str | None]) -> None:
        plain = [ODD_CHUNK.sub(" ", t) for t in texts if t]
        for a, b in blocks(plain):
            points, _ = block_of(plain[a:b])
            start, end = find_words(points)
            if not len(start):
                continue
            place, new = self.known.find(points, start, end)
            self.words += new
            self.counts = np.concatenate([self.counts, np.zeros(len(new), np.int64)])
            self.counts += np.bincount(place, minlength=len(self.counts))
