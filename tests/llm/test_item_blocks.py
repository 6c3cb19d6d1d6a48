"""A benchmark larger than one block (op3): passes one after the other give the rows of a single pass."""

from __future__ import annotations

from shoal.llm import decontaminate


def test_blocks_give_the_same_rows(spark, monkeypatch):
    words = [f"w{i}" for i in range(60)]
    texts = [" ".join(words), None, "", " ".join(words[5:25]), " ".join(words[40:]) + " other " + " ".join(words[:12]), "short item here"]
    docs = spark.createDataFrame([(i, t, "x", [1]) for i, t in enumerate(texts)] + [(0, texts[3], "y", None)], "doc_id long, text string, __hit string, n_hit array<int>").drop("__hit")
    items = spark.createDataFrame([(f"q{i}", " ".join(words[i * 4 : i * 4 + 14])) for i in range(10)] + [("s", "short item"), ("n", None)], "item_id string, text string")
    run = lambda: sorted(map(repr, decontaminate.find_contamination(docs, items).collect()))
    cut = lambda: sorted(map(repr, decontaminate.remove_contamination(docs, items).collect()))
    one = run(), cut()
    monkeypatch.setattr(decontaminate, "ITEM_BYTES", 200)
    assert len(list(decontaminate._item_blocks(items, "item_id", "text"))) > 2
    assert (run(), cut()) == one
