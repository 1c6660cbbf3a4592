"""The recall classifier judges words once, not again in each pair."""

import re

from widefeat.functions import models


def test_signs_are_sought_in_words_only(monkeypatch):
    text = " ".join(f"word{i % 7}" if i % 3 else "plain" for i in range(500)) + " 3 = x"
    words = text.split()
    grams = [*words, *map(" ".join, zip(words, words[1:], strict=False))]
    sought = []

    class Counted:
        def search(self, gram):
            sought.append(gram)
            return re.search(r"[0-9+=<>/^%]", gram)

    monkeypatch.setattr(models, "MATH_SIGNS", Counted())
    got = [models.math_one(text, q) for q in (0.1, 0.5, 0.9)]  # first, as weights may be kept
    assert all(" " not in g for g in sought)
    want = [models.math_weight(g) for g in grams]
    score = models.sigmoid(models.MATH[2] * sum(want) / len(want) + models.MATH[3])
    assert got == [score * q > 0.3 for q in (0.1, 0.5, 0.9)]
