"""Buckets dealt to several tasks (op2) link what brute force links."""

from __future__ import annotations

import random

from shoal.llm import jaccard_join


def test_classes_with_spread_buckets(spark, monkeypatch):
    monkeypatch.setattr(jaccard_join, "SPREAD", 2)
    monkeypatch.setattr(jaccard_join, "LEADERS", (2,))
    draw = random.Random(11)
    common = [f"c{i}" for i in range(12)]
    texts = []
    for k in range(24):
        own = [f"d{k // 3}w{i}" for i in range(40)]
        if k % 3:
            own[draw.randrange(40)] = f"x{k}"
        texts.append(" ".join(common + own))
    sets = [{tuple(t.split()[i : i + 4]) for i in range(len(t.split()) - 3)} for t in texts]
    parent = list(range(24))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(24):
        for j in range(i):
            if 100 * len(sets[i] & sets[j]) >= 85 * len(sets[i] | sets[j]):
                a, b = sorted((find(i), find(j)))
                parent[b] = a
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(2)
    got = {r["doc_id"]: r["component_id"] for r in jaccard_join.near_duplicates(docs).collect()}
    assert got == {i: find(i) for i in range(24)} and len(set(got.values())) < 24
