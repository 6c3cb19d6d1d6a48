"""Held-out losses of op9 against counts without the scored document; target keys joined instead of broadcast."""

from __future__ import annotations

import math
from collections import Counter

from shoal.llm import lm_scoring

TEXTS = {1: "a b a b c", 2: "a b", 3: "b c d", 4: "", 5: None, 6: "A b c d e f g", 7: "only here", 8: "a b a b c"}
GOOD = {1, 3, 4}


def _counts(keep):
    own, before, pair = Counter(), Counter(), Counter()
    for i in keep:
        w = (TEXTS[i] or "").lower().split()
        own.update(w)
        before.update([None, *w][: len(w)])
        pair.update(zip([None, *w], w, strict=False))
    return own, before, pair


def _check(spark):
    docs = spark.createDataFrame(list(TEXTS.items()), "doc_id long, text string").repartition(3)
    got = {r["doc_id"]: r for r in lm_scoring.score_documents(docs, spark.createDataFrame([(i,) for i in GOOD], "doc_id long"), held_out=True).collect()}
    assert set(got) == set(TEXTS)
    vocabulary = len({x for t in TEXTS.values() for x in (t or "").lower().split()})
    for i, t in TEXTS.items():
        w = (t or "").lower().split()
        if not w:
            assert got[i]["score"] is None
            continue
        losses = []
        for side in (GOOD, set(TEXTS) - GOOD):
            own, before, pair = _counts(side - {i})
            total = sum(own.values())
            losses.append(sum(-math.log((pair[p] + 4 * (own[p[1]] + 0.5) / (total + 0.5 * vocabulary)) / (before[p[0]] + 4)) for p in zip([None, *w], w, strict=False)) / len(w))
        assert abs(got[i]["target_loss"] - losses[0]) < 1e-8 and abs(got[i]["background_loss"] - losses[1]) < 1e-8
        assert abs(got[i]["score"] - (losses[0] - losses[1])) < 1e-8


def test_a_document_is_scored_without_its_own_counts(spark, monkeypatch):
    monkeypatch.setattr(lm_scoring, "CHUNK", 6)
    _check(spark)


def test_joined_keys_give_the_same_losses(spark, monkeypatch):
    monkeypatch.setattr(lm_scoring, "MOST_KEYS", 2)
    _check(spark)
