"""The sketch's ranks, and near-duplicate classes where one passage stands in most documents (op2)."""

from __future__ import annotations

import random

import numpy as np
from pyspark.sql import functions as F

from shoal.llm import jaccard_join, sketch


def test_ranks_never_fall_short(spark):
    draw = np.random.default_rng(3)
    hashes = draw.integers(0, 1 << 64, 50, np.uint64)
    times = [1] * 20 + [2] * 10 + [20] * 10 + [200] * 9 + [1100]
    rows = [(int(h.view(np.int64)),) for h, n in zip(hashes, times, strict=True) for _ in range(n)]
    df = spark.createDataFrame(rows, "h long").repartition(3)
    items = lambda b: iter([b.column(0).to_numpy().view(np.uint64)])
    found = sketch.repeated_items(df, [F.col("h")], items, ranked=True)
    again, rank = found(hashes), found.rank(hashes)
    for n, a, r in zip(times, again.tolist(), rank.tolist(), strict=True):
        assert a == (n > 1) and r == sum(n >= least for least in sketch.FREQUENT), (n, a, r)
    assert sketch.repeated_items(df, [F.col("h")], items)(hashes).tolist() == again.tolist()


def test_classes_around_a_frequent_passage(spark):
    draw = random.Random(17)
    passage = [f"p{i}" for i in range(30)]
    texts = []
    for k in range(60):
        own = [f"d{k // 2}w{i}" for i in range(25)]
        if k % 2:
            own[draw.randrange(25)] = "other"
        texts.append(" ".join(passage + own if k % 3 else own + passage))
    sets = [{tuple(t.split()[i : i + 4]) for i in range(len(t.split()) - 3)} for t in texts]
    want = list(range(60))
    for _ in range(60):
        for i in range(60):
            for j in range(i):
                if 100 * len(sets[i] & sets[j]) >= 85 * len(sets[i] | sets[j]):
                    want[i] = want[j] = min(want[i], want[j])
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    got = {r["doc_id"]: r["component_id"] for r in jaccard_join.near_duplicates(docs).collect()}
    assert got == dict(enumerate(want)) and 30 <= len(set(want)) < 60
