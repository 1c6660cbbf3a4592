"""New words are taken from a block together, not one by one."""

import numpy as np

from widefeat.llm import tokens


def test_new_words_are_stored_at_once(monkeypatch):
    texts = ["Über naïve words, 12 of them; it's one-two", "a", "", "x" * 70_000, " ".join(f"w{i}é" for i in range(3000))]
    points, _ = tokens.block_of(texts)
    start, end = tokens.find_words(points)
    want = [tokens.word_at(points, a, b) for a, b in zip(start, end, strict=True)]
    calls = []
    monkeypatch.setattr(tokens, "word_at", lambda p, a, b: calls.append(a) or p[a:b].tobytes().decode("utf-32-le"))
    table = tokens.WordTable()
    place, new = table.find(points, start, end)
    assert not calls
    assert [new[k] for k in place] == want and len(set(new)) == len(new) == len(table)
    assert [bytes(table.letters[a : a + n].astype("<u4")).decode("utf-32-le") for a, n in zip(table.first, table.sizes, strict=True)] == new
    again, none = table.find(points, start, end)
    assert none == [] and np.array_equal(again, place)
