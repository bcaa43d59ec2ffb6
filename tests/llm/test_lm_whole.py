"""Losses over all words, against counts by hand and the dense tables."""

import collections
import math
import random

import numpy as np
import pytest

from echowalk.llm import lm_scoring


def test_all_words_are_told_apart(spark):
    rng = random.Random(4)
    texts = [[f"r{rng.randint(0, 5000)}" if rng.random() < 0.7 else f"c{rng.randint(0, 20)}" for _ in range(rng.randint(1, 120))] for _ in range(150)]
    assert len({w for t in texts for w in t}) > 2500
    good = set(range(0, 150, 4))
    df = spark.createDataFrame([*((i, " ".join(t)) for i, t in enumerate(texts)), (150, None)], "doc_id long, text string").repartition(3)
    got = {r["doc_id"]: r for r in lm_scoring.score_documents(df, spark.createDataFrame([(i,) for i in good], "doc_id long")).collect()}
    v = len({w for t in texts for w in t}) + 1

    def model(keep):
        pair, ahead, one = collections.Counter(), collections.Counter(), collections.Counter()
        for i, t in enumerate(texts):
            if i in keep:
                pair.update(zip(["^", *t], t))
                ahead.update(["^", *t[:-1]])
                one.update(t)
        n = sum(one.values())
        p1 = lambda w: (one[w] + 0.5) / (n + 0.5 * v)
        return lambda a, w: -math.log2(0.7 * pair[a, w] / ahead[a] + 0.3 * p1(w) if ahead[a] else p1(w))

    t, b = model(good), model(set(range(150)))
    for i, x in enumerate(texts):
        assert got[i]["n_words"] == len(x)
        assert got[i]["target_loss"] == pytest.approx(np.mean([t(*p) for p in zip(["^", *x], x)]), abs=1e-4)
        assert got[i]["background_loss"] == pytest.approx(np.mean([b(*p) for p in zip(["^", *x], x)]), abs=1e-4)
    assert (got[150]["n_words"], got[150]["score"]) == (0, None)


def test_without_target_as_dense(spark):
    df = spark.createDataFrame([(1, "a b a"), (1, "a b a"), (None, "b c"), (2, "")], "doc_id long, text string")
    none = spark.createDataFrame([], "doc_id long")
    whole, dense = (sorted((tuple(r) for r in lm_scoring.score_documents(df, none, size).collect()), key=repr) for size in (None, 50))
    assert len(whole) == 4
    for x, y in zip(whole, dense):
        assert x[:2] == y[:2] and x[2:] == pytest.approx(y[2:], abs=1e-5)
