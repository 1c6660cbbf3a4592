"""Operators 4, 5 and 7: exact counts against brute force, held-out accuracy, odd rows."""

import math
import re
import zlib
from collections import Counter

import numpy as np

from widefeat.llm import language_id, quality_rules, toxicity
from widefeat.llm.common import read_table
from widefeat.llm.queries import queries

ODD = [(0, None, None), (1, "", "en"), (2, "123 !!! ...", "en"), (3, "a b c a b c a b c", None), (3, "a b c a b c a b c", None), (None, "no id here", "fr"), (6, "\n\nx y\nx y\n \nz\n", "de"), (7, "über " * 40_000, "de"), (8, "#a|b <c> & * $ % d\x0be", "en")]
SCHEMA = "doc_id long, text string, lang string"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def is_held_out(doc_id):
    return doc_id is not None and zlib.crc32(str(doc_id).encode()) % 3 == 1


def brute_counts(text):
    text = text or ""
    words = WORD.findall(text)
    windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    often = Counter(windows)
    repeated = {i + k for i, w in enumerate(windows) if often[w] > 1 for k in range(3)}
    lines = [x for x in text.split("\n") if WORD.search(x)]
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for w in words for c in w), len(lines) - len(set(lines)), len(repeated)


def check_counts(rows, got):
    want = sorted((str(d), *(c := brute_counts(t)), c[0] < 50 or 100 * c[4] > 50 * c[0]) for d, t in rows)
    assert sorted((str(r.doc_id), *(r[c] for c in quality_rules.COUNTS), r.base_failed) for r in got) == want
    assert not any(r.kept and r.base_failed for r in got)


def test_op5_counts_and_native_plan(spark, mid_dir):
    docs = read_table(spark, mid_dir, "documents").select("doc_id", "text")
    result = queries()["op5_decision_list_quality"](spark, mid_dir)
    plan = result._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)
    got = result.collect()
    check_counts([tuple(r) for r in docs.collect()], got)
    quality = {r.doc_id: r.quality for r in read_table(spark, mid_dir, "labels").collect()}
    judged = [(r.kept, quality[r.doc_id]) for r in got if is_held_out(r.doc_id) and r.doc_id in quality and not r.base_failed]
    assert all(kept for kept, good in judged if good) and np.mean([not kept for kept, good in judged if not good]) > 0.8


def test_op5_odd(spark):
    odd = spark.createDataFrame(ODD, SCHEMA)
    check_counts([r[:2] for r in ODD], quality_rules.judge(odd, []).collect())
    labels = spark.createDataFrame([(1, None), (None, 1), (3, 0)], "doc_id long, quality int")
    assert quality_rules.fit(odd, labels) == [] == quality_rules.fit(odd.limit(0), labels.limit(0))
    assert quality_rules.judge(odd.limit(0), []).count() == 0
    assert quality_rules.keep(odd, [], ("doc_id", "text")).columns == ["doc_id", "text"]


def test_decision_list_finds_planted_rules():
    rnd = np.random.default_rng(4)
    rows = []
    for _ in range(600):
        x = dict.fromkeys(quality_rules.FEATURES, 0.5) | {"symbol_share": rnd.random(), "upper_share": rnd.random(), "mean_word": rnd.random()}
        rows.append((x, int(x["symbol_share"] > 0.8 or (x["upper_share"] > 0.7 and x["mean_word"] <= 0.4))))
    rules = quality_rules.learn_rules(rows)
    wrong = sum(any(r.holds(x) for r in rules) != bool(y) for x, y in rows)
    assert 2 <= len(rules) <= 8 and wrong < 20


def test_op7(spark, mid_dir):
    docs = {r.doc_id: r for r in read_table(spark, mid_dir, "documents").collect()}
    got = queries()["op7_language_mixture"](spark, mid_dir).collect()
    assert sorted(r.doc_id for r in got) == sorted(docs) and all(0 <= r.score <= 1 for r in got)
    assert all(r.held_out == is_held_out(r.doc_id) for r in got)
    assert np.mean([r.lang_pred == docs[r.doc_id].lang for r in got if r.held_out]) > 0.95


def test_op7_mixtures_and_odd(spark, mid_dir):
    docs = read_table(spark, mid_dir, "documents")
    model = language_id.fit(docs)
    one, two = (next(r.text for r in docs.collect() if r.lang == k and 600 < r.n_chars < 3000 and "|" not in r.text) for k in ("de", "en"))
    lang, score, found = model.predict(one + " " + two[: len(one) // 2])
    assert lang == "de" and 0.5 < score < 0.85 and {x for x, _ in found} == {"de", "en"}
    assert model.predict(one)[2] == [("de", 1.0)]
    odd = spark.createDataFrame(ODD, SCHEMA)
    got = language_id.identify(odd, model).collect()
    assert len(got) == len(ODD) and {r.doc_id for r in got if r.lang_pred == "und"} == {0, 1, 2}
    assert all(r.lang_pred == "und" for r in language_id.identify(odd, language_id.fit(odd.limit(0))).collect())
    assert language_id.keep(odd, model).count() == len(ODD) - 3 and language_id.identify(odd.limit(0), model).count() == 0


def test_op7_counts_every_text(spark, small_dir):
    docs = read_table(spark, small_dir, "documents")
    model = language_id.fit(docs, smoothing=0.5)
    want = np.zeros((len(model.languages), language_id.BUCKETS))
    for r in docs.collect():
        if r.lang and not is_held_out(r.doc_id):
            np.add.at(want[model.languages.index(r.lang)], language_id.trigrams(r.text), 1)
    want += 0.5
    assert np.allclose(model.likelihood, want / want.sum(axis=1, keepdims=True), rtol=1e-5)


def test_op4(spark):
    sf_dir = "/root/testdata/sf0.1"
    toxic = {r.doc_id: r.toxic for r in read_table(spark, sf_dir, "labels").collect()}
    got = [r for r in queries()["op4_ftrl_toxicity"](spark, sf_dir).collect()]
    assert len(got) == 10_000 and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.7) and r.held_out == is_held_out(r.doc_id) for r in got)
    judged = [(r.predicted, toxic[r.doc_id]) for r in got if r.held_out and r.doc_id in toxic]
    assert np.mean([y for p, y in judged if p]) > 0.9 and np.mean([p for p, y in judged if y]) > 0.6
    clean = [p for p, y in judged if not y]
    assert np.mean(clean) < 0.01
    scores = [(r.score, toxic[r.doc_id]) for r in got if r.held_out and r.doc_id in toxic]
    limit = np.quantile([s for s, y in scores if not y], 0.9)  # a tenth of the clean ones lie above
    assert np.mean([s > limit for s, y in scores if y]) > 0.9


def plain_ftrl(rows, order, bits, alpha, beta, l1, l2):
    """The method coordinate by coordinate, without arrays."""
    z, n, bias = {}, {}, 1 << bits

    def weight(i):
        zi, strength = z.get(i, 0.0), 0.0 if i == bias else l1
        if abs(zi) <= strength:
            return 0.0
        return -(zi - (strength if zi > 0 else -strength)) / ((beta + math.sqrt(n.get(i, 0.0))) / alpha + (0.0 if i == bias else l2))

    for k in order:
        features, y = rows[k]
        own = {i: weight(i) for i in [*features, bias]}
        g = 1 / (1 + math.exp(-max(-35.0, min(35.0, sum(own.values()))))) - y
        for i, w in own.items():
            sigma = (math.sqrt(n.get(i, 0.0) + g * g) - math.sqrt(n.get(i, 0.0))) / alpha
            z[i] = z.get(i, 0.0) + g - sigma * w
            n[i] = n.get(i, 0.0) + g * g
    return {i: w for i in z if (w := weight(i)) or i == bias}


def test_ftrl_as_the_plain_method():
    rnd = np.random.default_rng(12)
    seen, rows = set(), []
    while len(rows) < 120:
        at = np.unique(rnd.integers(0, 200, rnd.integers(1, 30))).astype(np.int32)
        if at.tobytes() not in seen:
            seen.add(at.tobytes())
            rows.append((at, int(rnd.random() < 0.3 + 0.5 * (7 in at))))
    options = dict(bits=8, alpha=0.7, beta=0.9, l1=0.8, l2=0.3)
    model = toxicity.train(rows, passes=3, seed=11, **options)
    order = np.random.default_rng(11)
    want = plain_ftrl([(at.tolist(), y) for at, y in rows], [i for _ in range(3) for i in order.permutation(len(rows))], **options)
    got = dict(zip(model.at.tolist(), model.weight.tolist(), strict=True)) | {1 << 8: model.bias}
    assert got.keys() == want.keys() and 5 < len(got) < 200
    assert all(math.isclose(got[i], w, rel_tol=1e-5, abs_tol=1e-6) for i, w in want.items())


def test_op4_long_texts_are_scored_whole(spark):
    docs = spark.createDataFrame([(i, "x " * (300_000 if i == 2 else 50) + ("you awful fool" if i % 2 == 0 else "all is well")) for i in range(1, 5)], "doc_id long, text string")
    model = toxicity.train([(np.unique(toxicity.features(t)), y) for k in range(60) for t, y in ((f"a{k} x you awful fool", 1), (f"b{k} x all is well", 0))], l1=1.0)
    scores = {r.doc_id: r.score for r in toxicity.score(docs, model).collect()}
    assert scores[2] > 0.7 and abs(scores[2] - scores[4]) < 1e-9 and scores[1] < 0.3


def test_op4_odd(spark):
    odd = spark.createDataFrame(ODD, SCHEMA)
    labels = spark.createDataFrame([(1, 1), (None, 1), (3, None), (7, 0)], "doc_id long, toxic int")
    model = toxicity.fit(odd, labels)
    got = toxicity.score(odd, model).collect()
    assert len(got) == len(ODD) and len({r.score for r in got if r.doc_id in (0, 1)}) == 1
    assert toxicity.score(odd.limit(0), toxicity.fit(odd.limit(0), labels.limit(0))).count() == 0


def test_ftrl_learns_a_skip_gram():
    rnd = np.random.default_rng(2)
    rows = []
    for i in range(400):
        middle = f"w{rnd.integers(50)}"
        text = f"x{rnd.integers(50)} you {middle} fool y{rnd.integers(50)}" if i % 2 else f"fool {middle} x{rnd.integers(50)} you z"
        rows.append((np.unique(toxicity.features(text)), i % 2))
    model = toxicity.train(rows, l1=1.0)
    dense = model.dense()
    margins = [(model.margin(dense, toxicity.features(f"q you {w} fool r")), model.margin(dense, toxicity.features(f"fool {w} q you r"))) for w in "abc"]
    assert all(a > 0 > b for a, b in margins) and len(model.at) < 200
