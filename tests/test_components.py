"""Connected components: one task and distributed rounds give the same labels."""

from __future__ import annotations

import random

from shoal.core import components
from shoal.core.storage import Scratch


def _labels(edges):
    label = {x: x for e in edges for x in e}
    for _ in label:
        for u, v in edges:
            label[u] = label[v] = min(label[u], label[v])
    return label


def test_both_ways_against_brute_force(spark, monkeypatch):
    draw = random.Random(5)
    chain = [(i, i + 1) for i in range(100, 140)]
    draw.shuffle(chain)
    edges = chain + [(draw.randrange(60) - 20, draw.randrange(60) - 20) for _ in range(30)] + [(7, 7), (300, 200), (200, 300), (1 << 60, 200)]
    df = spark.createDataFrame(edges, "u long, v long").repartition(3)
    want = _labels([e for e in edges if e[0] != e[1]])
    for small in (500_000, 0):
        monkeypatch.setattr(components, "SMALL", small)
        got = {r["id"]: r["label"] for r in components.star_labels(df, Scratch(spark, "test")).collect()}
        assert got == want
    monkeypatch.setattr(components, "SMALL", 500_000)
    assert components.star_labels(df.limit(0), Scratch(spark, "test")).count() == 0
