"""Batched runs, contraction and measures on arcs in parts, against joins."""

import pytest

from shoal import experiments
from shoal.core.graph import Graph, contract
from shoal.core.storage import Scratch
from shoal.graphs import builders
from shoal.measures import agreement, quality
from shoal.operators import multilevel, onetask, parts, propagation

FOLDER = "/root/testdata/sf0.001"


def rows(df, *columns):
    return sorted(map(tuple, df.select(*columns).collect()))


@pytest.fixture(scope="module")
def pair(spark):
    """The same graph with loops, without and with parts."""
    g = builders.planted(spark, FOLDER)[0]
    loops = g.nodes.where("id % 3 = 0").selectExpr("id AS u", "id AS v", "id % 5 + 1 AS w")
    scratch = Scratch(spark, "test")
    g = Graph(scratch.write(g.edges.unionByName(loops)), scratch.write(g.nodes))
    with pytest.MonkeyPatch.context() as m:
        m.setattr(parts, "PART_ARCS", 500)
        cut = propagation.in_parts(g, scratch)
    assert cut.parts.parts > 3
    return g, cut


def test_contraction_and_measures_agree(pair):
    groups = pair[0].nodes.selectExpr("id", "id % 7 AS comm")
    stats = [rows(quality.community_stats(g, groups), "comm", "size", "vol", "inner_w", "cut_w") for g in pair]
    small = [contract(g, groups) for g in pair]
    assert stats[0] == stats[1]
    assert rows(small[0][0].edges, "u", "v", "w") == rows(small[1][0].edges, "u", "v", "w")
    assert rows(small[0][0].nodes, "id") == rows(small[1][0].nodes, "id")
    assert quality.modularity(pair[0], groups).first() == quality.modularity(pair[1], groups).first()


def test_edge_rand_agrees(pair):
    first, second = (pair[0].nodes.selectExpr("id", f"id % {k} AS comm") for k in (7, 3))
    assert agreement.edge_rand(pair[0], first, second).first() == agreement.edge_rand(pair[1], first, second).first()


def test_mixing_of_large_graphs_is_that_of_small_ones(spark, monkeypatch):
    """Graphs beyond one task's arrays: each run is one task over their parts; coarse graphs are beyond them as well."""
    tell = lambda: rows(experiments.mixing(spark, FOLDER, list(experiments.OWN), (3, 8)), "mixing", "algo", "communities", "modularity", "edge_rand")
    want = tell()
    monkeypatch.setattr(experiments, "_SUITES", {})
    monkeypatch.setattr(onetask, "SMALL_ARCS", 100)
    monkeypatch.setattr(parts, "PART_ARCS", 500)
    monkeypatch.setattr(parts, "_on_spark", lambda table, n, k, on=parts._on_spark: lambda fn, *a: on(table, n, k)(fn, *a) if fn.__name__ in ("_inner_of", "_agreeing") else 1 / 0)
    assert tell() == want


def test_an_assignment_of_some_nodes_is_joined(pair):
    groups = pair[0].nodes.where("id % 2 = 0").selectExpr("id", "id % 4 AS comm")
    stats = [rows(quality.community_stats(g, groups), "comm", "size", "vol", "inner_w", "cut_w") for g in pair]
    assert stats[0] == stats[1]


def test_batched_runs_on_parts_are_not_joined(pair, monkeypatch):
    """Each as in one task; before, a broadcast state was joined to all arcs for all runs at once."""
    want = rows(propagation.propagate_batch(pair[0], 3, ties="hash", seed=5), "run", "id", "comm")
    monkeypatch.setattr(propagation, "label_weights", None)  # what the joins begin with
    assert rows(propagation.propagate_batch(pair[0], 3, ties="hash", seed=5, state="broadcast"), "run", "id", "comm") == want


def test_methods_cut_a_large_graph_once(spark, monkeypatch):
    want = {a: rows(m(builders.planted(spark, FOLDER)[0], 0, propagation.RunLog()), "id", "comm") for a, m in experiments.OWN.items()}
    cut, cuts = parts.cut, []
    monkeypatch.setattr(parts, "cut", lambda edges, *k: cuts.append(edges) or cut(edges, *k))
    monkeypatch.setattr(onetask, "SMALL_ARCS", 1500)
    s = experiments.Suite(spark, FOLDER)
    for a in ("LP", "MLR", "ENS"):
        s.run(a, "planted")
        assert rows(s.found[a, "planted"], "id", "comm") == want[a]
    written = s.light("planted").edges
    assert sum(e is written for e in cuts) == 1
