"""Operators 1 to 3 against the tokenizers library on whole texts."""

import hashlib
import random
import zlib
from pathlib import Path

import numpy as np
import pytest
from tokenizers import Tokenizer

from widefeat.llm import packing, token_files, tokens, transducer
from widefeat.llm.common import read_table
from widefeat.llm.queries import queries
from widefeat.llm.tokens import library_encoder, tokenizer_path

ODD = [(0, None, "x"), (1, "", "x"), (2, "Ünïcode  naïve “quotes” 😀 \x0b <|endoftext|>tail 'S don't", "x"), (2, "again", "x"), (None, "no id", "x"), (5, "a" * 5000, "x"), (6, "word " * 3000, "x"), (7, "word " * 3000, "x")]


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(tokenizer_path())


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, "doc_id long, text string, ids string")


def ids_of(library, text, *end):
    return np.asarray([*library.encode(text or "", add_special_tokens=False).ids, *end], dtype="<u4").tobytes()


def corpus(spark, sf_dir):
    return [(r.doc_id, r.text) for r in read_table(spark, sf_dir, "documents").select("doc_id", "text").collect()]


def expected_files(library, rows):
    out, start = [], 0
    for doc_id, text in sorted(rows):
        ids = ids_of(library, text, 2)
        out.append((doc_id, start, len(ids) // 4, zlib.crc32(ids)))
        start += len(ids) // 4
    return out


def test_words_as_library(library):
    rnd, encoder, codec = random.Random(7), library_encoder(tokenizer_path()), transducer.TransducerCodec(tokenizer_path())
    letters = [chr(c) for c in [*range(1, 0x250), 0x300, 0x3A3, 0x3C3, 0x2019, 0x1F600, 0x2028, 0x3000, 0x4E2D, 0x212B, 0xFB01, 0x661]]
    for k in range(3000):
        text = "".join(rnd.choice(letters) if rnd.random() < 0.5 else rnd.choice(" abcE'sSthe\n19") for _ in range(rnd.randint(0, 40))) + "<|endoftext|>x" * (k % 5 == 0)
        want = ids_of(library, text)
        assert encoder.encode([text])[0] == want == codec.encode([text])[0], text
        ids = np.frombuffer(want, "<u4").tolist()
        assert codec.decode(ids) == library.decode(ids, skip_special_tokens=False)


def test_op1_whole(spark, small_dir, library):
    got = sorted(map(tuple, queries()["op1_token_files"](spark, small_dir).select("doc_id", "start", "n_tokens", "ids_crc32").collect()))
    assert got == expected_files(library, corpus(spark, small_dir))


def test_op1_odd_and_empty(spark, odd, library):
    got = token_files.token_digest(odd).orderBy("start").collect()
    assert [r.doc_id for r in got] == [None, 0, 1, 2, 2, 5, 6, 7]
    assert [r.start for r in got] == [0, *np.cumsum([r.n_tokens for r in got])[:-1].tolist()]
    by_id = {r.doc_id: r.ids_crc32 for r in got if r.doc_id != 2}
    assert all(by_id[i] == zlib.crc32(ids_of(library, t, 2)) for i, t, _ in ODD if i != 2)
    assert token_files.token_digest(odd.limit(0)).count() == 0


def test_op1_selective_reads(spark, small_dir):
    files = token_files.write_token_files(read_table(spark, small_dir, "documents"), shards=4)
    part = token_files.read_token_files(spark, files, ("doc_id", "n_tokens"), first_id=10, last_id=19)
    assert sorted(r.doc_id for r in part.collect()) == list(range(10, 20))
    plan = part._jdf.queryExecution().toString()
    assert "ids" not in plan.split("ReadSchema")[1].split("\n")[0] and "GreaterThanOrEqual(doc_id,10)" in plan


def test_op2_whole(spark, small_dir, odd, library):
    for rows, got in ((corpus(spark, small_dir), queries()["op2_transducer_codec"](spark, small_dir)), ([r[:2] for r in ODD], transducer.codec_digest(odd)), ([], transducer.codec_digest(odd.limit(0)))):
        want = []
        for doc_id, text in rows:
            ids = ids_of(library, text)
            decoded = library.decode(np.frombuffer(ids, "<u4").tolist(), skip_special_tokens=False)
            want.append((doc_id, len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(decoded.encode()).hexdigest()))
        assert sorted(map(tuple, got.collect()), key=str) == sorted(want, key=str)


def test_automaton_is_minimal_and_exact():
    words = sorted(w.encode() for w in ("tap", "taps", "top", "tops", "stop", "stops", "a", "é"))
    arcs, _ = transducer.minimal_automaton(words)
    lexicon = transducer.Lexicon.of_buffer(transducer.Lexicon.compile({w: [i] for i, w in enumerate(words)}).to_bytes())
    assert len(lexicon.accepts) < 12 <= sum(map(len, words))
    assert lexicon.find([*words, b"to", b"tapsx", b"zz", b""]).tolist() == [*range(len(words)), -1, -1, -1, -1]


def test_plan_windows():
    rnd = random.Random(3)
    for _ in range(30):
        counts = {rnd.randint(1, 100): rnd.randint(1, 30) for _ in range(rnd.randint(1, 40))}
        patterns = packing.plan_windows(counts, 100)
        placed = {}
        for p in patterns:
            assert sum(n * k for n, k in p.take) <= 100
            for n, k in p.take:
                placed[n] = placed.get(n, 0) + k * p.times
        assert placed == counts
    fill = packing.closest_fill({7: 2, 5: 3, 3: 1}, [7, 5, 3], 18)
    assert sum(n * k for n, k in fill.items()) == 18


def check_packing(library, rows, packed, capacity=2048):
    texts, pieces, used = {}, {}, {}
    for doc_id, text in rows:
        texts.setdefault(doc_id, []).append(ids_of(library, text, 1))
    for r in packed:
        pieces.setdefault(r.doc_id, []).append((r.start, r.length, r.ids_crc32, r.doc_tokens))
        used.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert pieces.keys() == texts.keys()
    for doc_id, got in pieces.items():
        want = [(a // 4, len(x[a : a + 4 * capacity]) // 4, zlib.crc32(x[a : a + 4 * capacity]), len(x) // 4) for x in texts[doc_id] for a in range(0, len(x), 4 * capacity)]
        assert sorted(got) == sorted(want)
    assert sorted(used) == list(range(len(used)))
    for spans in used.values():
        end = 0
        for offset, length in sorted(spans):
            assert offset == end
            end += length
        assert end <= capacity


def test_op3_whole(spark, small_dir, odd, library):
    packed = queries()["op3_minimum_slack_packing"](spark, small_dir)
    check_packing(library, corpus(spark, small_dir), packed.collect())
    assert packing.padding_share(packed).first().share < 0.02
    check_packing(library, [r[:2] for r in ODD], packing.pack(odd).collect())
    assert packing.pack(odd.limit(0)).count() == 0


def thue_morse(n, letters="ab"):
    return "".join(letters[bin(i).count("1") % 2] for i in range(n))


ALIKE = [(i, f"x {thue_morse(n, pair)} y {thue_morse(n, pair[::-1])}") for i, (n, pair) in enumerate((n, pair) for n in (1024, 2048, 4096) for pair in ("ab", "ba"))]


def test_words_of_equal_polynomial_hashes(spark, library):
    """Such words and their complements collide under every polynomial hash modulo 2**64."""
    docs = spark.createDataFrame(ALIKE, "doc_id long, text string").coalesce(1)
    got = sorted(tuple(r[c] for c in ("doc_id", "start", "n_tokens", "ids_crc32")) for r in token_files.token_digest(docs).collect())
    assert got == expected_files(library, ALIKE)
    assert {(r.doc_id, r.ids_sha256) for r in transducer.codec_digest(docs).collect()} == {(i, hashlib.sha256(ids_of(library, t)).hexdigest()) for i, t in ALIKE}
    check_packing(library, ALIKE, packing.pack(docs).collect())


def test_words_are_told_apart_by_letters(library, monkeypatch, small_dir, spark):
    """Nothing rests on the hashes: with only 97 of them all ids are still right, and so are the counts."""
    whole = tokens.hashes_of
    monkeypatch.setattr(tokens, "hashes_of", lambda *a: whole(*a) % np.uint64(97))
    texts = [t for _, t in corpus(spark, small_dir)][:40]
    base = library_encoder(tokenizer_path())
    encoder = tokens.WordEncoder(base.encode_words, base.encode_raw, most=700)
    assert encoder.encode(texts) == [ids_of(library, t) for t in texts]
    counts, want = tokens.WordCounts(), tokens.WordCounts()
    counts.add(texts)
    monkeypatch.undo()
    want.add(texts)
    assert dict(zip(counts.words, counts.counts.tolist(), strict=True)) == dict(zip(want.words, want.counts.tolist(), strict=True))


def test_lexicon_takes_the_most_frequent_words(spark):
    docs = spark.createDataFrame([(i, " ".join(f"word{'abcdefghij'[j // 10]}{'abcdefghij'[j % 10]}" for j in range(100) if i % (1 + j // 10) == 0)) for i in range(90)], "doc_id long, text string")
    often = {f"word{a}{b}": sum(i % (1 + k) == 0 for i in range(90)) for k, a in enumerate("abcdefghij") for b in "abcdefghij"}
    for most in (0, 1, 15, 64, 100, 500):
        words = transducer.frequent_words(docs, most)
        assert len(words) == min(most, 100)
        least = min((often[w] for w in words), default=0)
        assert all(w in words for w, n in often.items() if n > least) or not words


def test_op1_footers(spark, small_dir):
    """Encodings, row groups and page indexes are as the writer was told."""
    import pyarrow.parquet as pq

    files = token_files.write_token_files(read_table(spark, small_dir, "documents"), shards=2, row_group_mb=1, page_kb=16)
    seen = []
    for path in sorted(Path(files.path.removeprefix("file:")).glob("*.parquet")):
        meta = pq.ParquetFile(path).metadata
        for g in range(meta.num_row_groups):
            columns = {meta.row_group(g).column(c).path_in_schema: meta.row_group(g).column(c) for c in range(meta.num_columns)}
            ids = next(c for name, c in columns.items() if name.startswith("ids"))
            assert {"RLE_DICTIONARY", "PLAIN_DICTIONARY"} & set(ids.encodings) and ids.has_dictionary_page
            for name in ("doc_id", "row", "n_tokens", "local_start"):
                assert "DELTA_BINARY_PACKED" in columns[name].encodings and not columns[name].has_dictionary_page
                assert columns[name].has_offset_index and columns[name].has_column_index
            assert ids.has_offset_index
            seen.append(meta.row_group(g).num_rows)
    assert sum(seen) == 200
