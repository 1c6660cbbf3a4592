"""Text features take time in proportion to the text, and share what they have in common."""

import time

import pytest
from pyspark.sql import functions as F

from widefeat.functions import library


def test_mail_pattern_is_linear_in_long_words(spark):
    """A word of 400,000 letters: a pattern that begins with a run of them tries each as a start and reads on to the end."""
    rows = spark.createDataFrame([(1, "a" * 400_000), (2, "a" * 400_000 + "@b.c"), (3, "@b.c"), (4, "a@b..c"), (5, None), (6, "a 555-1234")], "i int, t string")
    began = time.time()
    got = {r.i: r.v for r in rows.select("i", F.expr(library.expressions("t")["pii_flag"][1]).alias("v")).collect()}
    assert got == {1: False, 2: True, 3: False, 4: False, 5: None, 6: True}
    assert time.time() - began < 20


def test_stop_words_are_picked_once():
    shared = library.lets("t")
    stops = next(n for n in shared if n.startswith("_stops"))
    assert all(stops in shared[f"_{k}_t"] and "_words" not in shared[f"_{k}_t"] for k in library.STOP_WORDS)


@pytest.mark.parametrize("n", [2, 3])
def test_repeated_windows(spark, n):
    texts = ["", "a", "a b", "a b a b a b", "x y z x y z", "one  two\tthree one two three four"]
    words = library._words("t")
    got = [r.v for r in spark.createDataFrame([(t,) for t in texts], "t string").coalesce(1).select(F.expr(library._ngram_rep(words, True, n)).alias("v")).collect()]
    for t, v in zip(texts, got, strict=True):
        w = t.split()
        grams = [tuple(w[i : i + n]) for i in range(len(w) - n + 1)]
        assert v == pytest.approx(1 - len(set(grams)) / len(grams) if grams else 0.0)
