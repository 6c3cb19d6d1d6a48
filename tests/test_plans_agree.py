"""One result whatever the physical plan: one task, broadcast state, shuffled state, batched runs, packed or wide keys."""

from __future__ import annotations

import pytest

from shoal.core.graph import Graph
from shoal.graphs import builders
from shoal.operators import baselines, ensemble, moves, multilevel, propagation
from shoal.sources import generators


def as_dict(df):
    return {r["id"]: r["comm"] for r in df.collect()}


def graph(spark, edges):
    return Graph.of(spark.createDataFrame(edges, "u long, v long, w long"))


@pytest.fixture(scope="module")
def tails(spark):
    g, _ = generators.planted_heavy_tail(spark, 120, 0.3, least_degree=3, most_degree=8, least_size=8, most_size=20)
    return Graph(g.edges.persist(), g.nodes.persist())


@pytest.mark.parametrize("options", [{}, {"ties": "hash", "seed": 5, "frontier": False}, {"schedule": "random", "weighted": False, "stop": "majority"}])
def test_propagation(tails, options):
    logs = [propagation.RunLog() for _ in range(3)]
    found = [as_dict(propagation.propagate_labels(tails, state=s, log=log, max_rounds=6, **options)) for s, log in zip(("task", "broadcast", "shuffle"), logs, strict=True)]
    assert found[0] == found[1] == found[2]
    figures = [[(r["round"], r["slot"], r["updated"], r["active"]) for r in log.rows] for log in logs]
    assert figures[0] == figures[1] == figures[2] and logs[0].settled == logs[1].settled


def test_batched_runs_are_the_single_runs(tails):
    rows = {(r["run"], r["id"]): r["comm"] for r in propagation.propagate_batch(tails, 2, ties="hash", seed=3, state="broadcast", max_rounds=4).collect()}
    for run in (0, 1):
        one = as_dict(propagation.propagate_labels(tails, ties="hash", seed=3 + run, state="shuffle", max_rounds=4))
        assert one == {i: c for (r, i), c in rows.items() if r == run}


def test_moves_and_levels(tails):
    for k in ({"max_rounds": 2}, {"max_rounds": 1, "schedule": "independent"}):
        assert as_dict(moves.local_move(tails, state="task", **k)[0]) == as_dict(moves.local_move(tails, state="shuffle", **k)[0])
    k = {"refine": True, "max_rounds": 2, "slots": 2}
    assert as_dict(multilevel.multilevel(tails, state="task", **k)) == as_dict(multilevel.multilevel(tails, state="broadcast", **k))
    assert as_dict(baselines.agglomerate(tails, "star")) == as_dict(baselines.agglomerate(tails, "star", state="shuffle"))


def test_ensemble_modes_agree(tails):
    assert as_dict(ensemble.ensemble(tails, b=2, mode="batched")) == as_dict(ensemble.ensemble(tails, b=2, mode="threads"))


def test_large_weights_and_ids(spark):
    top = 2**62
    g = graph(spark, [(1, 2, 3 * 10**9), (2, 3, 10**9), (1, top, 10**9), (top, top + 1, 4 * 10**9), (3, 4, 5 * 10**9)])
    for ties in ("keep_min", "min", "hash"):
        found = as_dict(propagation.propagate_labels(g, ties=ties, state="shuffle", max_rounds=12))
        assert found == {1: 1, 2: 1, 3: 3, 4: 3, top: top, top + 1: top}


def test_two_nodes_do_not_swap_for_ever(spark):
    pairs = [(2 * i, 2 * i + 1, 1) for i in range(400)]
    log = propagation.RunLog()
    found = as_dict(propagation.propagate_labels(graph(spark, pairs), log=log))
    assert log.settled and all(found[2 * i] == found[2 * i + 1] for i in range(400))


def test_unsettled_runs_say_so(spark):
    log = propagation.RunLog()
    with pytest.warns(RuntimeWarning, match="not settled"):
        propagation.propagate_labels(generators.path(spark, 60), log=log, max_rounds=1)
    assert log.settled is False


def test_keys_that_do_not_fit_are_an_error(spark, tmp_path):
    rows = [(1, 0), (1, 1), (1, 2000)]
    spark.createDataFrame(rows, "conv_id long, turn long").write.parquet(f"{tmp_path}/a/conversations.parquet")
    g = builders.turns(spark, f"{tmp_path}/a")
    assert g.nodes.count() == 3 and g.edges.count() == 1
    spark.createDataFrame([(1, 1 << 24)], "conv_id long, turn long").write.parquet(f"{tmp_path}/b/conversations.parquet")
    with pytest.raises(Exception, match="does not fit"):
        builders.turns(spark, f"{tmp_path}/b").nodes.collect()


def test_groups_beyond_the_bound_are_an_error(spark):
    rows = spark.createDataFrame([(1, i) for i in range(5)], "k long, i long")
    assert builders.cooccurrence(rows, "k", "i", max_group=5).edges.count() == 10
    with pytest.raises(Exception, match="more than 4 members"):
        builders.cooccurrence(rows, "k", "i", max_group=4).edges.collect()
