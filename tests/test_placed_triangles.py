"""Triangles by arrays against brute force and against triples of parts, in every way of counting them."""

import itertools
import random

import numpy as np
import pytest

from shoal.core import components
from shoal.core.graph import Graph
from shoal.core.storage import Scratch
from shoal.measures import profile, triangles


def _random(spark, share: float):
    rng = random.Random(11)
    pairs = {p for p in itertools.combinations(range(60), 2) if rng.random() < share}
    want: dict[int, int] = {}
    for x, y, z in itertools.combinations(range(60), 3):
        if {(x, y), (x, z), (y, z)} <= pairs:
            for i in (x, y, z):
                want[i] = want.get(i, 0) + 1
    # ids far apart, one loop, ends in both orders, a node without edges
    rows = [(*((7 * x, 7 * y) if (x + y) % 2 else (7 * y, 7 * x)), 1) for x, y in pairs] + [(21, 21, 1)]
    nodes = spark.createDataFrame([(7 * i,) for i in range(60)] + [(10_000,)], "id long")
    return Graph(spark.createDataFrame(rows, "u long, v long, w long"), nodes), {7 * i: n for i, n in want.items()}


@pytest.mark.parametrize("share", [0.1, 0.7])
@pytest.mark.parametrize("per_wedge", [0, 100, 10**9])
def test_every_way_counts_the_same(spark, monkeypatch, share, per_wedge):
    """per_wedge 0: all wedges are looked up; 10^9: all tiles are multiplied."""
    for name, value in {"PER_WEDGE": per_wedge, "PART_EDGES": 40, "GROUP_EDGES": 200, "HELD_EDGES": 90, "WEDGES": 25, "CELLS": 200, "TILE_ROWS": 8, "TILE_LISTS": 5, "TILE_COLUMNS": 16, "PIECE": 17}.items():
        monkeypatch.setattr(triangles, name, value)
    g, want = _random(spark, share)
    assert {r["id"]: r["triangles"] for r in profile.triangles(g).collect()} == want


def test_more_nodes_than_the_driver_numbers(spark, monkeypatch):
    monkeypatch.setattr(triangles, "PLACED", 10)
    monkeypatch.setattr(profile, "TRIANGLE_EDGES", 50)
    g, want = _random(spark, 0.3)
    assert {r["id"]: r["triangles"] for r in profile.triangles(g).collect()} == want


def test_no_edges(spark):
    g = Graph(spark.createDataFrame([], "u long, v long, w long"), spark.range(3))
    assert profile.triangles(g).collect() == []


def test_edges_travel_once(spark):
    """An edge travels in eight bytes; before, it travelled once a part of the nodes."""
    g, _ = _random(spark, 0.5)
    ids, rank = np.append(np.arange(0, 420, 7), 10_000), np.arange(61)
    plan = g.edges.select("u", "v").mapInArrow(lambda batches: triangles._dealt(batches, ids, rank, 3), "part int, src binary, dst binary")
    assert sum(len(r["src"]) + len(r["dst"]) for r in plan.collect()) == 8 * g.edges.where("u <> v").count()


def test_components_are_cut_down_in_tasks(spark, monkeypatch):
    monkeypatch.setattr(components, "FOREST", 20)
    rng = random.Random(3)
    pairs = [(rng.randrange(40), rng.randrange(40)) for _ in range(300)] + [(100 + rng.randrange(30), 100 + rng.randrange(30)) for _ in range(25)]
    root = {i: i for p in pairs for i in p}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for u, v in pairs:
        a, b = sorted((find(u), find(v)))
        root[b] = a
    want = {i: find(i) for p in pairs if p[0] != p[1] for i in p}
    edges = spark.createDataFrame(pairs, "u long, v long").repartition(3)
    for small in (0, 500_000):
        monkeypatch.setattr(components, "SMALL", small)
        assert {r["id"]: r["label"] for r in components.star_labels(edges, Scratch(spark, "test")).collect()} == want
