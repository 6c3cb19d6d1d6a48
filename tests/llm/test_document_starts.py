"""Benchmark passages at the start of documents of one shard (op3), against brute force."""

from __future__ import annotations

import random

import numpy as np
import pyarrow as pa

from shoal.llm.decontaminate import Phrases, ShardIndex, search_shard


def _brute(words: list[str], items: dict[str, list[str]], width: int) -> tuple[list[int], set[str]]:
    hit, found = set(), set()
    for name, item in items.items():
        for k in range(max(1, len(item) - width + 1)):
            window = item[k : k + width]
            for at in range(len(words) - len(window) + 1):
                if words[at : at + len(window)] == window:
                    hit.update(range(at, at + len(window)))
                    found.add(name)
    return sorted(hit), found


def test_no_walk_crosses_a_document_end():
    index = ShardIndex(np.array([3, 0, 2, 0, 3, 2, 0, 2, 3, 0]), 4)
    low, high = int(index.before[2]), int(index.before[3])
    assert sorted(index.locate(np.arange(low, high)).tolist()) == [2, 5, 7]


def test_shards_of_documents_that_open_with_benchmark_words():
    draw = random.Random(5)
    items = {"a": "red green blue".split(), "b": "blue red".split(), "c": ["green"], "d": "red red blue green".split()}
    vocabulary = ["red", "green", "blue", "x", "y"]
    phrases = Phrases.of([(k, " ".join(v)) for k, v in items.items()], 3)
    for _ in range(40):
        docs = [[draw.choice(vocabulary) for _ in range(draw.randrange(7))] for _ in range(30)]
        got = search_shard([pa.array([" ".join(d) for d in docs], pa.string())], phrases)
        for words, (n, hit, found) in zip(docs, got, strict=True):
            assert (n, hit.tolist(), {phrases.names[i] for i in found}) == (len(words), *_brute(words, items, 3))
