"""Graphs held by classes of equal nodes: every method gives what it gives on all pairs, and graphs whose pairs are too many run."""

from __future__ import annotations

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from shoal import experiments
from shoal.core.graph import Graph, contract
from shoal.graphs import builders
from shoal.measures import quality
from shoal.operators import baselines, ensemble, moves, multilevel, propagation, twins


def as_dict(df):
    return {r["id"]: r["comm"] for r in df.collect()}


def both(spark, rows):
    """The graph of these (group, item) rows by its pairs and by its classes."""
    rows = spark.createDataFrame(rows, "k string, i long").persist()
    g = builders.cooccurrence(rows, "k", "i")
    g = Graph(g.edges.persist(), g.nodes.persist())
    return g, Graph(g.edges, g.nodes, builders.cooccurrence_twins(rows, "k", "i"))


@pytest.fixture(scope="module")
def pair(spark):
    rng = random.Random(4)
    sets = [rng.sample(range(12), rng.randint(1, 3)) for _ in range(9)] + [[99]]
    return both(spark, [(f"h{h}", i * i) for i in range(60) for h in sets[rng.randrange(len(sets))]] + [("h99", 5000), ("h100", 5001)])


METHODS = {
    "lp": propagation.propagate_labels,
    "lp_hash": lambda g: propagation.propagate_labels(g, ties="hash", seed=3, theta=0),
    "lp_original": baselines.original_label_propagation,
    "independent": lambda g: moves.local_move(g, schedule="independent", max_rounds=3)[0],
    "refined": lambda g: multilevel.multilevel(g, refine=True),
    "ensemble": ensemble.ensemble,
    "star": baselines.agglomerate,
    "matching": lambda g: baselines.agglomerate(g, "matching"),
    "sequential": baselines.sequential_multilevel,
    "greedy": baselines.randomized_greedy,
    "cores": lambda g: baselines.core_group_ensemble(g, iterate=True, b=2),
}


@pytest.mark.parametrize("name", list(METHODS))
def test_methods_agree(pair, name):
    assert pair[1].held_twins is not None
    assert as_dict(METHODS[name](pair[1])) == as_dict(METHODS[name](pair[0]))


def test_batches_agree_with_the_distributed_ones(pair):
    found = [as_dict(baselines.randomized_greedy_batch(g, max_rounds=3, **k)) for g, k in ((pair[0], {"state": "shuffle"}), (pair[0], {}), (pair[1], {}))]
    assert found[0] == found[1] == found[2]


def test_hash_is_sparks(spark):
    ids = [0, 1, 7, 2**40 + 3, 2**62]
    rows = spark.createDataFrame([(i,) for i in ids], "id long").select("id", F.xxhash64("id", F.lit(1007)).alias("h")).collect()
    assert [r["h"] for r in rows] == twins.xxhash64(np.array(ids), 1007).tolist()


def test_measures_and_contraction_agree(pair):
    groups = pair[0].nodes.select("id", (F.col("id") % 5).alias("comm"))
    stats = [sorted(map(tuple, quality.community_stats(g, groups).select("comm", "size", "vol", "inner_w", "cut_w").collect())) for g in pair]
    small = [contract(g, groups)[0] for g in pair]
    edges = [sorted(map(tuple, s.edges.select("u", "v", "w").collect())) for s in small]
    assert stats[0] == stats[1] and edges[0] == edges[1]
    assert as_dict(multilevel.multilevel(small[1])) == as_dict(multilevel.multilevel(small[0]))


def test_more_pairs_than_a_serial_method_takes(spark):
    g = both(spark, [(k, i) for i in range(2_400) for k in (("a", "x") if i % 2 else ("b", "x"))] + [("c", 3_000), ("c", 3_001)])[1]
    assert g.held_twins.pairs * 2 > baselines.MAX_ARCS
    for method in (baselines.sequential_multilevel, baselines.randomized_greedy, baselines.core_group_ensemble):
        found = as_dict(method(g))
        assert len(found) == 2_402 and found[3_001] == found[3_000] == 3_000 and found[0] != 3_000


def test_numbers_beyond_63_bits():
    """Total weights of 2^34 to 2^40: scores leave 63 bits, results stay those of exact numbers."""
    cls, w = np.repeat(np.arange(4), 3), np.array([[9, 1, 0, 2], [1, 8, 3, 0], [0, 3, 7, 1], [2, 0, 1, 6]])
    a, b = np.nonzero(np.triu(w))
    small, large = (twins.TwinGraph.of(np.arange(12), cls, np.ones(12), a, b, w[a, b] * f) for f in (1, 1 << 33))
    everyone = np.ones(12, bool)
    for guard in (True, False):
        x, y = (g.best_moves(g.ids, g.vol, g.total, (1, 1), everyone, guard) for g in (small, large))
        assert x[0].tolist() == y[0].tolist() and x[1].tolist() == y[1].tolist()
    assert small.partners(small.total).tolist() == large.partners(large.total).tolist()
    assert small.node_at_a_time(1).tolist() == large.node_at_a_time(1).tolist()
    assert small.random_merges(1, 2).tolist() == large.random_merges(1, 2).tolist()


def test_a_suite_that_wrote_the_pairs_still_runs_on_classes(spark, tmp_path):
    rows = [(i, "".join(f'<a href="http://{h}/">' for h in (["a", "x"] if i % 2 else ["b", "x"]))) for i in range(30)]
    spark.createDataFrame(rows, "page_id long, html string").write.parquet(f"{tmp_path}/pages.parquet")
    found = []
    for first in (False, True):
        s = experiments.Suite(spark, str(tmp_path))
        if first:
            s.graph("pagepages")
        assert s.light("pagepages").held_twins is not None
        found.append(s.run("MLR", "pagepages")[2:4] + s.run("MLR", "pagepages")[6:8])
    assert found[0] == found[1]
