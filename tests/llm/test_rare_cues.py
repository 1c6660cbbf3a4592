"""Operator 4 learns cues that few rows of a full sample hold."""

import random

import numpy as np

from widefeat.llm import toxicity


def test_rare_cues_get_weight_in_a_full_sample():
    rnd = random.Random(8)
    common, cues = [f"w{i}" for i in range(400)], [f"slur{i}" for i in range(40)]
    rows = []
    for i in range(toxicity.MOST_ROWS):
        words = rnd.choices(common, k=20)
        if i < 800:  # each cue in 20 toxic rows and no clean one
            words[rnd.randrange(20)] = cues[i % 40]
        rows.append((np.unique(toxicity.features(" ".join(words))), int(i < 800)))
    model = toxicity.train(rows)
    dense = model.dense()
    margin = lambda text: model.margin(dense, toxicity.features(text))
    fresh = [rnd.choices(common, k=20) for _ in cues]
    clean = np.array([margin(" ".join(w)) for w in fresh])
    toxic = np.array([margin(" ".join([*w, c])) for w, c in zip(fresh, cues, strict=True)])
    assert (toxic > 0).mean() > 0.9 and (clean < 0).mean() > 0.9
