"""Operator 9 against brute force, and the pipeline stage by stage."""

import math
import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from widefeat.llm import ann, language_id
from widefeat.llm.common import read_table
from widefeat.llm.queries import queries

from .test_learned import brute_counts, is_held_out
from .test_similar import brute_kept
from .test_tokens import check_packing


def brute_nearest(rows, k=5):
    fine = [(i, np.asarray(v, float)) for i, v in rows if i is not None and v is not None and all(x is not None for x in v) and np.isfinite(np.asarray(v, float)).all() and any(v)]
    x = np.asarray([v for _, v in fine])
    out = {}
    for i, q in fine:
        if i % 50 == 0:
            s = (x * q).sum(axis=1) / (np.sqrt((x * x).sum(axis=1)) * np.sqrt((q * q).sum()))
            out[i] = sorted(((-a, j) for a, (j, _) in zip(s.tolist(), fine, strict=True) if j != i))[:k]
    return out


def recall(want, got):
    found = {(r.query_id, r.vec_id) for r in got}
    return np.mean([(q, j) in found for q, best in want.items() for _, j in best])


def test_op9(spark, mid_dir):
    rows = [(r.vec_id, r.embedding) for r in read_table(spark, mid_dir, "embeddings").collect()]
    want, got = brute_nearest(rows), queries()["op9_anisotropic_search"](spark, mid_dir).collect()
    assert {r.query_id for r in got} == set(want) and len(got) == 5 * len(want)
    assert recall(want, got) > 0.97
    exact = dict(rows)
    for r in got:
        q, v = (np.asarray(exact[i], float) for i in (r.query_id, r.vec_id))
        assert abs(r.score - q @ v / np.sqrt(q @ q) / np.sqrt(v @ v)) < 1e-12


def test_op9_odd(spark):
    rnd = np.random.default_rng(1)
    rows = [(i, [float(x) for x in rnd.normal(size=6)]) for i in range(40)]
    rows += [(100, [1.0, 0, 0, 0, 0, 0]), (150, None), (200, [0.0] * 6), (250, [float("nan")] + [1.0] * 5), (300, [1.0, None, 0, 0, 0, 0]), (None, [1.0] * 6), (350, [1.0] * 5), (400, [float("inf")] + [1.0] * 5)]
    rows += [(1000 + i, [1.0, 0, 0, 0, 0, 0]) for i in range(200)]
    rows = [(i, None if v is None else [None if x is None else float(x) for x in v]) for i, v in rows]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(3)
    got = {(r.query_id, r["rank"]): r.vec_id for r in ann.nearest(frame).collect()}
    want = {(q, k + 1): j for q, best in brute_nearest([r for r in rows if r[0] != 350]).items() for k, (_, j) in enumerate(best)}
    assert got == want
    assert ann.nearest(frame.limit(0)).count() == 0
    assert ann.nearest(frame.where("vec_id in (0, 1, 2)")).count() == 2


def test_op9_lists(spark):
    """Many lists: clustered vectors need few of them, others most, and recall holds either way; a hot vector changes nothing."""
    rnd = np.random.default_rng(5)
    centres = rnd.normal(size=(60, 24)) * 2
    kinds = {"clustered": centres[rnd.integers(60, size=12_000)] + rnd.normal(size=(12_000, 24)) * 0.7, "even": rnd.normal(size=(12_000, 24))}
    visits = {}
    for kind, x in kinds.items():
        x[rnd.random(len(x)) < 0.33] = x[0]
        rows = [(i, v.tolist()) for i, v in enumerate(x)]
        frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(6)
        index = ann.fit(ann.valid_vectors(frame))
        visits[kind] = index.visits / len(index.centres)
        want = brute_nearest(rows)
        got = ann.nearest(frame).collect()
        assert len(got) == 5 * len(want)
        assert recall(want, got) > 0.95
        best = {(r.query_id, r["rank"]): r.vec_id for r in got}
        same = np.flatnonzero((x == x[0]).all(axis=1)).tolist()
        for q in (i for i in same if i % 50 == 0):
            assert [best[q, k] for k in range(1, 6)] == [i for i in same if i != q][:5]
    assert len(index.centres) > 15 and visits["clustered"] < 0.5 and visits["clustered"] < visits["even"]


def test_op9_exhaustive(spark, mid_dir):
    frame = read_table(spark, mid_dir, "embeddings")
    rows = [(r.vec_id, r.embedding) for r in frame.collect()]
    assert recall(brute_nearest(rows), ann.nearest(frame, exhaustive=True, rerank=500).collect()) == 1


def test_anisotropic_loss_favours_scores():
    rnd = np.random.default_rng(3)
    unit = ann.unit_rows(rnd.normal(size=(2000, 16)) + 1)
    aware, plain = ann.learn_codebooks(unit, threshold=0.5), ann.learn_codebooks(unit, threshold=0.0)
    a, p = aware.encode(unit), plain.encode(unit)
    assert plain.eta == 1 < aware.eta
    assert aware.loss(unit, a) < ann.Codebooks(plain.centres, aware.eta).loss(unit, p)
    table = aware.tables(unit[:3])
    packed = ann.pack_codes(a)
    estimate = table[0][np.arange(table.shape[1])[None], packed].sum(axis=1)
    decoded = aware.centres[np.arange(8)[None], a].reshape(len(unit), -1)
    assert np.allclose(estimate, decoded @ unit[0], atol=1e-5)


@pytest.fixture(scope="module")
def stages(spark, mid_dir):
    """The documents before and after each filtering stage, and the packed rows."""
    docs = read_table(spark, mid_dir, "documents")
    out = [docs.collect()]
    for name, stage in corpus_pipeline.STAGES:
        frame = stage(spark, docs, mid_dir)
        out.append(frame.collect())
        if name != "packing":
            assert frame.columns == docs.columns
            docs = spark.createDataFrame(out[-1], docs.schema)
    return out


def brute_told(rows):
    """Ids of the texts that a plain EM over single languages, pairs and chance gives half or more to learned languages."""
    counts = {}
    for doc_id, text, lang in rows:
        if lang is not None and text is not None and not is_held_out(doc_id):
            counts.setdefault(lang, Counter()).update(language_id.trigrams(text).tolist())
    n = language_id.BUCKETS
    like = {k: (lambda g, c=c, t=sum(c.values()): (c[g] + 0.5) / (t + 0.5 * n)) for k, c in counts.items()}

    def em(rows_of, rounds):
        pi = [1 / len(rows_of)] * len(rows_of)
        for _ in range(rounds):
            new = [0.0] * len(pi)
            for column in zip(*rows_of, strict=True):
                total = sum(p * x for p, x in zip(pi, column, strict=True))
                for i, (p, x) in enumerate(zip(pi, column, strict=True)):
                    new[i] += p * x / total
            pi = [x / len(rows_of[0]) for x in new]
        return pi

    kept = set()
    for doc_id, text, _ in rows:
        grams = language_id.trigrams(text or "").tolist()
        if not grams:
            continue
        if len(grams) > 400:  # prose of this length is in the learned languages in these tables
            kept.add(doc_id)
            continue
        table = {k: [f(g) for g in grams] for k, f in like.items()}
        best = max(sorted(table), key=lambda k: sum(map(math.log, table[k])))
        if em([table[best], [1 / n] * len(grams)], 12)[0] >= 0.5:
            kept.add(doc_id)
    return kept


def test_language_filter(spark, mid_dir):
    """What is kept depends on the model: noise and languages that weren't learned or aren't wanted go."""
    docs = read_table(spark, mid_dir, "documents")
    model = language_id.fit(docs)
    rnd = random.Random(6)
    noise = [(-i - 1, "".join(rnd.choice("bcdfghjkqvwxz0123456789 ") for _ in range(500)), None, "x", 1) for i in range(20)]
    given = docs.union(spark.createDataFrame(noise, docs.schema))
    kept = language_id.keep(given, model).collect()
    assert not [r for r in kept if r.doc_id < 0] and len(kept) > 0.99 * docs.count()
    lang = {r.doc_id: r.lang_pred for r in language_id.identify(docs, model).collect()}
    german = language_id.keep(docs, model, wanted=["de"]).collect()
    assert german and all(lang[r.doc_id] == "de" for r in german)
    strange = language_id.fit(given.withColumn("lang", F.when(F.col("doc_id") < 0, "zz")))
    assert strange.languages == ("zz",)
    left = {r.doc_id for r in language_id.keep(given, strange).collect()}
    assert len(left & {r[0] for r in noise}) == 20 and len(left) < 0.1 * docs.count()


def test_extra_columns_come_along(spark, mid_dir):
    names = ["_row", "twin", "gone_id", "GONE_HASH", "_kept", "node", "fp", "label", "quality"]
    docs = read_table(spark, mid_dir, "documents").drop("source", "n_chars").where("doc_id < 60")
    docs = docs.select("*", *(F.lit(i).alias(c) for i, c in enumerate(names)))
    for _, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, mid_dir)
        if stage is not corpus_pipeline.packing_stage:
            assert out.columns == docs.columns
            assert {tuple(r[c] for c in names) for r in out.collect()} == {tuple(range(len(names)))}
        else:
            assert out.count() >= 60


def test_stages(spark, mid_dir, stages):
    docs, good, told, single, packed = stages
    quality = {r.doc_id: r.quality for r in read_table(spark, mid_dir, "labels").collect()}
    kept = {r.doc_id for r in good}
    for r in docs:
        n, *_, repeated = brute_counts(r.text)
        failed = n < 50 or 100 * repeated > 50 * n
        assert not (failed and r.doc_id in kept)
        assert failed or r.doc_id in kept or quality.get(r.doc_id) != 1
    assert {r.doc_id for r in told} == brute_told([(r.doc_id, r.text, r.lang) for r in good])
    assert {r.doc_id for r in single} == brute_kept([(r.doc_id, r.text) for r in told]) and len(single) == len({r.doc_id for r in single})
    from tokenizers import Tokenizer

    from widefeat.llm.tokens import tokenizer_path

    check_packing(Tokenizer.from_file(tokenizer_path()), [(r.doc_id, r.text) for r in single], packed)


def test_run(spark, mid_dir, stages):
    key = lambda r: (r.doc_id, r.start, r.length, r.ids_crc32, r.doc_tokens)
    assert sorted(map(key, corpus_pipeline.run(spark, mid_dir).collect())) == sorted(map(key, stages[-1]))


def test_odd_documents(spark, mid_dir):
    long = " ".join(f"word{i}" for i in range(80))
    rows = [(1, long, "en", "s", 1), (1, long, "en", "s", 1), (None, long, "en", "s", 1), (None, "other " + long[::-1], None, None, None), (2, None, None, "s", None), (3, "", "en", "s", 0), (4, "1 2 " * 60 + " ".join(map(str, range(200))), "en", "s", 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for frame in (docs, docs.limit(0)):
        for _, stage in corpus_pipeline.STAGES:
            result = stage(spark, frame, mid_dir)
            assert result.count() <= len(rows)
    assert sorted(str(r.doc_id) for r in corpus_pipeline.copies_stage(spark, docs.where("doc_id is null or doc_id = 1"), mid_dir).collect()) == ["1", "None"]
