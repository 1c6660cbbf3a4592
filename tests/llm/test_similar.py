"""The pipeline's near-duplicate stage against brute-force Jaccard similarity."""

import random

import corpus_pipeline
from widefeat.llm.common import read_table

from .test_shards_and_copies import brute_components


def brute_set(text):
    words = (text or "").encode().lower().split()
    return frozenset(tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4)))


def brute_kept(rows):
    """The least doc_id of each component of texts at 0.8 or more."""
    sets = {i: brute_set(t) for i, t in rows}
    holders = {}
    for i, s in sets.items():
        for g in s:
            holders.setdefault(g, []).append(i)
    edges = set()
    for i, s in sets.items():
        shared = {}
        for g in s:
            for j in holders[g]:
                if j > i:
                    shared[j] = shared.get(j, 0) + 1
        edges |= {(i, j) for j, n in shared.items() if 9 * n >= 4 * (len(s) + len(sets[j]))}
    label = brute_components(sorted(sets), sorted(edges))
    least = {}
    for i in sorted(sets):
        least.setdefault(label[i], i)
    return set(least.values())


def test_stage_keeps_one_of_each_similar_group(spark, mid_dir):
    """Every copy at 0.8 or more goes, however many SimHash bits differ; nothing else does."""
    rnd = random.Random(4)
    given = [(r.doc_id, r.text) for r in read_table(spark, mid_dir, "documents").collect()]
    planted, at = [], max(i for i, _ in given) + 1
    for _ in range(12):
        base = [f"w{rnd.randrange(5000)}" for _ in range(200)]
        for k in range(25):
            words = list(base)
            for _ in range(k % 6):
                words[rnd.randrange(200)] = f"x{rnd.randrange(10**6)}"
            planted.append((at, " ".join(words)))
            at += 1
    rows = given + planted
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long").repartition(5)
    assert {r.doc_id for r in corpus_pipeline.copies_stage(spark, docs, mid_dir).collect()} == brute_kept(rows)
