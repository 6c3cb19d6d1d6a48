"""Work that shares the cluster gives what it gives one after the other."""

from __future__ import annotations

import statistics
import threading
from concurrent.futures import ThreadPoolExecutor

from shoal import experiments
from shoal.core.storage import Scratch
from shoal.graphs import builders
from shoal.operators import baselines, propagation


def test_a_scratch_gives_each_thread_its_own_table(spark):
    scratch = Scratch(spark, "threads")
    with ThreadPoolExecutor(8) as pool:
        tables = list(pool.map(lambda i: scratch.write(spark.range(i, i + 1)), range(24)))
    assert len({t._scratch_path for t in tables}) == 24 and [t.first()[0] for t in tables] == list(range(24))


def test_batched_runs_keep_their_order_and_log(spark):
    g, log = builders.planted(spark, "/root/testdata/sf0.001")[0], propagation.RunLog()
    found = {(r["run"], r["id"]): r["comm"] for r in propagation.propagate_batch(g, 3, seed=2, ties="hash", log=log).collect()}
    rows = []
    for run in range(3):
        one_log = propagation.RunLog()
        one = propagation.propagate_labels(g, seed=2 + run, ties="hash", log=one_log).collect()
        assert all(found[run, r["id"]] == r["comm"] for r in one)
        rows += [(r["round"], r["slot"], r["updated"]) for r in one_log.rows]
    assert [(r["round"], r["slot"], r["updated"]) for r in log.rows] == rows and log.settled is not None


def test_mixing_is_told_in_the_order_of_graphs(spark):
    rows = experiments.mixing(spark, "/root/testdata/sf0.001", ["LP", "ML"], (1, 5, 9)).collect()
    assert [(r["mixing"], r["algo"]) for r in rows] == [(m, a) for m in (0.1, 0.5, 0.9) for a in ("LP", "ML")]
    for r in rows:
        g, truth = builders.planted(spark, "/root/testdata/sf0.001", round(10 * r["mixing"]))
        found = experiments.METHODS[r["algo"]](g, 0, propagation.RunLog())
        assert found.select("comm").distinct().count() == r["communities"]


def test_core_group_runs_on_a_small_graph_share_the_cluster(spark, monkeypatch):
    g, greedy, meet = builders.geo(spark, "/root/testdata/sf0.001"), baselines.randomized_greedy, threading.Barrier(4)

    def together(graph, k, seed):
        if seed < 4:
            meet.wait(60)  # all four runs have begun before one goes on
        return greedy(graph, k, seed)

    monkeypatch.setattr(baselines, "LIGHT_ARCS", -1, raising=False)
    alone = {r["id"]: r["comm"] for r in baselines.core_group_ensemble(g).collect()}
    monkeypatch.undo()
    monkeypatch.setattr(baselines, "randomized_greedy", together)
    assert {r["id"]: r["comm"] for r in baselines.core_group_ensemble(g).collect()} == alone


def test_resolution_tells_what_single_runs_find_and_measures_nothing(spark, monkeypatch):
    monkeypatch.setattr(experiments, "_SUITES", {})
    meet, lp = threading.Barrier(2), experiments.OWN["LP"]

    def together(g, seed, log):
        meet.wait(60)  # both graphs have begun before one goes on
        return lp(g, seed, log)

    monkeypatch.setattr(experiments, "METHODS", experiments.METHODS | {"LP": together})
    rows = experiments.resolution(spark, "/root/testdata/sf0.001", ["geo", "turns"], ["LP", "ML"]).collect()
    measured = experiments.suite(spark, "/root/testdata/sf0.001").rows
    monkeypatch.undo()
    assert [(r["graph"], r["algo"]) for r in rows] == [(n, a) for n in ("geo", "turns") for a in ("LP", "ML")]
    assert not measured
    for r in rows:
        sizes = [x["count"] for x in experiments.METHODS[r["algo"]](experiments.GRAPHS[r["graph"]](spark, "/root/testdata/sf0.001"), 0, propagation.RunLog()).groupBy("comm").count().collect()]
        assert (r["communities"], r["largest"], r["median"]) == (len(sizes), max(sizes), statistics.median(sizes))
