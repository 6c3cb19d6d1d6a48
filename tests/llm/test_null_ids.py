"""Rows without an id beside equal texts (op2)."""

from __future__ import annotations

from shoal.llm import jaccard_join


def test_a_row_without_an_id_does_not_stand_for_its_set(spark):
    text = " ".join(f"n{i}" for i in range(200))
    rows = [(None, text), (5, text), (3, f"{text} end")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)
    got = {r["doc_id"]: r["component_id"] for r in jaccard_join.near_duplicates(docs).collect()}
    assert got == {None: None, 5: 3, 3: 3}
