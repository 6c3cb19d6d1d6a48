"""Losses of op9 against counts of real words and pairs, with more words than any fixed table has cells."""

from __future__ import annotations

import math
from collections import Counter

from shoal.llm import lm_scoring


def test_losses_are_those_of_real_counts(spark, monkeypatch):
    texts = {i: " ".join(f"w{i * 5000 + k}" for k in range(5000)) for i in range(20)}  # 100,000 distinct words
    texts |= {20: "w1 w2 W1 w2", 21: "w2 w1 w2", 22: "", 23: None, 24: "w7 w8 new"}
    good = {0, 1, 20}
    monkeypatch.setattr(lm_scoring, "CHUNK", 12_000)
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(2)
    got = {r["doc_id"]: r for r in lm_scoring.score_documents(docs, spark.createDataFrame([(i,) for i in good], "doc_id long")).collect()}
    assert set(got) == set(texts)
    sides = [(Counter(), Counter(), Counter()) for _ in range(2)]
    tokens = {i: (t or "").lower().split() for i, t in texts.items()}
    for i, w in tokens.items():
        own, before, pair = sides[0 if i in good else 1]
        own.update(w)
        before.update([None, *w][: len(w)])
        pair.update(zip([None, *w], w, strict=False))
    vocabulary = len({x for w in tokens.values() for x in w})
    for i, w in tokens.items():
        if not w:
            assert got[i]["n_tokens"] == 0 and got[i]["score"] is None
            continue
        want = []
        for own, before, pair in sides:
            total = sum(own.values())
            want.append(sum(-math.log((pair[p] + 4 * (own[p[1]] + 0.5) / (total + 0.5 * vocabulary)) / (before[p[0]] + 4)) for p in zip([None, *w], w, strict=False)) / len(w))
        row = got[i]
        assert row["n_tokens"] == len(w)
        for a, b in ((row["target_loss"], want[0]), (row["background_loss"], want[1]), (row["score"], want[0] - want[1])):
            assert abs(a - b) < 1e-8
