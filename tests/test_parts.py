"""Graphs in parts of whole nodes: the broadcast state gives what one task gives, over many parts and without a shuffle."""

from __future__ import annotations

import random

import pytest

from shoal import experiments
from shoal.core.graph import Graph
from shoal.core.storage import Scratch
from shoal.operators import moves, parts, propagation


def as_dict(df):
    return {r["id"]: r["comm"] for r in df.collect()}


@pytest.fixture(scope="module")
def blocks(spark):
    """Blocks of 15 nodes with some edges between them, a loop, isolated nodes."""
    rng, edges = random.Random(1), {(9, 9): 4}
    for _ in range(500):
        a = rng.randrange(90)
        b = a // 15 * 15 + rng.randrange(15) if rng.random() < 0.7 else rng.randrange(90)
        if a != b:
            edges[3 * min(a, b), 3 * max(a, b)] = rng.randint(1, 300)
    return Graph(spark.createDataFrame([(u, v, w) for (u, v), w in edges.items()], "u long, v long, w long").persist(), spark.createDataFrame([(3 * i,) for i in range(95)], "id long").persist())


@pytest.fixture(scope="module")
def cut(blocks, spark):
    size, kept = propagation.size_of(blocks), (parts.PART_ARCS, parts.DEALT)
    parts.PART_ARCS, parts.DEALT = 100, 64
    held = parts.cut(blocks.edges, blocks.nodes, size.edges, size.weight, Scratch(spark, "test"))
    parts.PART_ARCS, parts.DEALT = kept
    return Graph(blocks.edges, blocks.nodes, parts=held)


def test_parts_agree_with_one_task(blocks, cut):
    assert cut.parts.parts > 5 and cut.parts.total == blocks.total_weight()
    for options in ({}, {"ties": "hash", "seed": 5, "weighted": False}):
        logs = [propagation.RunLog() for _ in range(2)]
        found = [as_dict(propagation.propagate_labels(g, state=s, theta=-1, max_rounds=3, log=log, **options)) for g, s, log in zip((blocks, cut), ("task", "broadcast"), logs, strict=True)]
        assert found[0] == found[1]
        assert [(r["updated"], r["active"]) for r in logs[0].rows] == [(r["updated"], r["active"]) for r in logs[1].rows]
    for options in ({}, {"schedule": "independent"}):
        task, broadcast = moves.local_move(blocks, state="task", max_rounds=2, **options), moves.local_move(cut, state="broadcast", max_rounds=2, **options)
        assert as_dict(task[0]) == as_dict(broadcast[0]) and task[1] == broadcast[1]


def test_rounds_on_parts_shuffle_no_arcs(spark, cut):
    costs = experiments.stage_costs(spark, lambda: propagation.propagate_labels(cut, state="broadcast", rename=False, theta=-1, max_rounds=2))
    assert costs["shuffle_mb"] < 0.002  # counts of nodes and edges


def test_scaling_tells_equal_results(spark, blocks):
    for method in ("LP", "move"):
        rows = experiments.strong_scaling(spark, blocks, method).collect()
        assert [r["workers"] for r in rows] == [1, 2, 4] and all(r["same"] for r in rows)


def test_cached_weights_and_one_task_over_parts(blocks, cut):
    for options in ({"max_rounds": 3}, {"max_rounds": 2, "slots": 2, "guards": {"slots"}}):
        want = moves.local_move(blocks, state="task", **options)
        for variant in ({"state": "task"}, {"state": "broadcast", "weights": "delta"}, {"state": "shuffle"}):
            found = moves.local_move(cut, **variant, **options)
            assert as_dict(found[0]) == as_dict(want[0]) and found[1] == want[1]


def test_lean_and_dense_tell_equal_results(spark, blocks):
    rows = experiments.lean_against_dense(spark, blocks).collect()
    assert [r["variant"] for r in rows] == ["dense", "lean", "cached weights", "one task"] and all(r["same"] for r in rows)
