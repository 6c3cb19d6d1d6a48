"""The pipeline's near-duplicate stage: five-word shingles, 80 %, and rows that repeat an id."""

from __future__ import annotations

import corpus_pipeline


def _kept(spark, rows):
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    return sorted((r["doc_id"] is not None, r["doc_id"] or 0, r["text"]) for r in corpus_pipeline.near_duplicates(spark, docs, "").collect())


def test_copies_between_80_and_85_percent_go(spark):
    base = [f"c{i}" for i in range(900)]
    short = base[: 900 * 83 // 100]
    changed = [f"z{i}" if i % 47 == 23 else w for i, w in enumerate(base)]  # 19 words apart
    other = [f"o{i}" for i in range(900)]
    rows = [(1, " ".join(base)), (2, " ".join(short)), (3, " ".join(changed)), (4, " ".join(other))]
    assert [r[1] for r in _kept(spark, rows)] == [1, 4]


def test_only_the_copied_row_of_a_repeated_id_goes(spark):
    a, b, c = (" ".join(f"{k}{i}" for i in range(100)) for k in "abc")
    rows = [(1, a), (5, f"{a} end"), (5, b), (7, b), (8, c), (8, f"{c} end"), (None, a)]
    got = [(i if there else None, t) for there, i, t in _kept(spark, rows)]
    assert got[:3] == [(None, a), (1, a), (5, b)]
    assert len(got) == 4 and got[3][0] == 8
