"""Scores hold every method whatever the size of the graphs."""

import pytest

from shoal import experiments
from shoal.operators import baselines
from shoal.graphs import builders

FOLDER = "/root/testdata/sf0.001"


def test_scores_do_not_depend_on_a_bound_of_arcs(spark, monkeypatch):
    """Beyond MAX_ARCS the serial methods warn, and are measured and scored as below it."""
    monkeypatch.setattr(experiments, "_SUITES", {})
    monkeypatch.setattr(baselines, "MAX_ARCS", 1)
    found = {r["algo"]: r for r in experiments.measured_scores(spark, FOLDER, ["geo"]).collect()}
    assert set(found) == set(experiments.METHODS) and all(r["modularity_score"] is not None for r in found.values())


def test_serial_methods_give_the_same_beyond_the_bound(spark, monkeypatch):
    g = builders.geo(spark, FOLDER)
    below = [sorted(map(tuple, m(g).select("id", "comm").collect())) for m in (baselines.sequential_multilevel, baselines.randomized_greedy)]
    monkeypatch.setattr(baselines, "MAX_ARCS", 1)
    with pytest.warns(RuntimeWarning, match="one task"):
        beyond = [sorted(map(tuple, m(g).select("id", "comm").collect())) for m in (baselines.sequential_multilevel, baselines.randomized_greedy)]
    assert below == beyond


def test_a_method_that_fails_is_not_left_out_of_the_scores(spark, monkeypatch):
    def fails(g, seed, log):
        raise ValueError("not this graph")

    monkeypatch.setattr(experiments, "_SUITES", {})
    monkeypatch.setattr(experiments, "METHODS", {"ML": experiments.METHODS["ML"], "other": fails})
    with pytest.raises(ValueError, match="not this graph"):
        experiments.measured_scores(spark, FOLDER, ["geo"])
