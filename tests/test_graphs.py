"""Hand-made graphs with known values, invariants, and plans."""

import pytest
from pyspark.sql import functions as F

from shoal.core.graph import Graph, canonical, check_assignment, contract, index_nodes, lift, singletons
from shoal.measures import agreement, profile, quality
from shoal.operators import baselines, ensemble, moves, multilevel, propagation
from shoal.plans.inspect import shuffles
from shoal.sources import generators

TRIANGLES = [(0, 1), (0, 2), (1, 2), (3, 4), (3, 5), (4, 5), (2, 3)]


def graph(spark, edges, nodes=()):
    rows = [(*e, 1) if len(e) == 2 else e for e in edges]
    extra = spark.createDataFrame([(i,) for i in nodes], "id long") if nodes else None
    return Graph.of(spark.createDataFrame(rows, "u long, v long, w long"), extra)


def labels(spark, d):
    return spark.createDataFrame(sorted(d.items()), "id long, comm long")


def as_dict(df):
    return {r["id"]: r["comm"] for r in df.collect()}


@pytest.fixture(scope="module")
def two(spark):
    g = graph(spark, TRIANGLES)
    g.edges, g.nodes = g.edges.persist(), g.nodes.persist()
    return g


SPLIT = {0: 0, 1: 0, 2: 0, 3: 3, 4: 3, 5: 3}


def test_known_values(spark, two):
    two.validate()
    split = labels(spark, SPLIT)
    assert quality.coverage(two, split).first()["coverage"] == round(6 / 7, 6)
    assert quality.modularity(two, split).first()["modularity"] == round(5 / 14, 6)
    assert quality.modularity(two, labels(spark, dict.fromkeys(range(6), 0))).first()["modularity"] == 0
    assert quality.modularity(two, singletons(two)).first()["modularity"] == round(-34 / 196, 6)
    score = {(r["id"], r["to_comm"]): int(r["score"]) for r in moves.move_scores(two, split, 7).collect()}
    assert score[(2, 3)] / (2 * 49) == pytest.approx(-23 / 98)


def test_contract_keeps_modularity_and_volume(spark, two):
    small, mapping = contract(two, labels(spark, SPLIT))
    assert sorted(map(tuple, small.edges.collect())) == [(0, 0, 3), (0, 3, 1), (3, 3, 3)]
    assert {r["id"]: r["vol"] for r in small.node_stats.collect()} == {0: 7, 3: 7}
    assert quality.modularity(small, singletons(small)).first()["modularity"] == round(5 / 14, 6)
    assert as_dict(lift(mapping, singletons(small))) == SPLIT


def test_profile(spark, two):
    row = profile.profile(two).first()
    assert (row["n"], row["m"], row["max_degree"], row["components"]) == (6, 7, 3, 1)


def test_validate_rejects(spark):
    bad = Graph(spark.createDataFrame([(2, 1, 1), (1, 2, 0)], "u long, v long, w long"), spark.createDataFrame([(1,)], "id long"))
    with pytest.raises(ValueError, match="out of order"):
        bad.validate()


def test_methods_find_the_triangles(spark, two):
    for found in (multilevel.multilevel(two), multilevel.multilevel(two, refine=True), baselines.sequential_multilevel(two), baselines.agglomerate(two, "matching"), baselines.randomized_greedy(two, seed=1)):
        check_assignment(two, found)
        assert quality.modularity(two, found).first()["modularity"] == round(5 / 14, 6)


def test_propagation_isolated_and_frontier(spark):
    g = graph(spark, TRIANGLES, nodes=[9])
    on = as_dict(propagation.propagate_labels(g, frontier=True, max_rounds=8))
    off = as_dict(propagation.propagate_labels(g, frontier=False, max_rounds=8))
    assert on == off and on[9] == 9


def test_synchronous_swaps_and_stops(spark):
    log = propagation.RunLog()
    propagation.propagate_labels(graph(spark, [(0, 1)]), schedule="sync", frontier=False, max_rounds=9, log=log)
    assert any(r["phase"] == "cycle" for r in log.rows)


def test_weighted_and_unweighted_labels(spark):
    g = graph(spark, [(0, 1, 1), (0, 2, 1), (0, 3, 5)])
    state = labels(spark, {0: 0, 1: 7, 2: 7, 3: 3})
    assert as_dict(propagation.lp_step(g.arcs, state))[0] == 3
    assert as_dict(propagation.lp_step(g.arcs, state, weighted=False))[0] == 7


def test_consensus(spark):
    runs = spark.createDataFrame([(r, i, c) for r, run in enumerate(([1, 1, 2, 2], [1, 2, 2, 2])) for i, c in enumerate(run)], "run int, id long, comm long")
    want = {0: 0, 1: 1, 2: 2, 3: 2}
    for method in ("exact", "mul33", "xxhash64"):
        assert as_dict(ensemble.consensus_core(runs, method)) == want


def test_move_variants_agree(spark, two):
    plain = as_dict(moves.local_move(two)[0])
    assert as_dict(moves.local_move(two, weights="delta")[0]) == plain
    assert as_dict(moves.local_move(two, state="shuffle")[0]) == plain


def test_agreement(spark, two):
    a, b = labels(spark, SPLIT), singletons(two)
    assert agreement.edge_rand(two, a, a).first()["edge_rand"] == 1
    assert agreement.edge_rand(two, a, b).first()["agree"] == 1
    assert agreement.pair_rand(a, a).first().asDict() == {"pair_rand": 1.0, "adjusted_rand": 1.0, "nmi": 1.0}


def test_index_nodes_is_dense(spark):
    rows = index_nodes(spark.createDataFrame([(x,) for x in "dbacab"], "s string"), "s").orderBy("value").collect()
    assert [tuple(r) for r in rows] == [("a", 0), ("b", 1), ("c", 2), ("d", 3)]


def test_empty_graph(spark):
    g = graph(spark, [(0, 1)])
    none = Graph(g.edges.where("false"), g.nodes)
    assert as_dict(moves.local_move(none)[0]) == {0: 0, 1: 1}
    assert as_dict(canonical(singletons(none))) == {0: 0, 1: 1}


def test_broadcast_round_does_not_shuffle_arcs(spark):
    g = generators.ring_of_cliques(spark, 4, 4)
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        arcs = g.arcs.repartition("src").persist()
        arcs.count()
        state = singletons(g).persist()
        state.count()
        winner = propagation.dominant_labels(propagation.label_weights(arcs, state, broadcast=True))
        assert shuffles(winner) == 0 or "InMemoryTableScan" in winner._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.adaptive.enabled")


def test_generators_do_not_depend_on_partitions(spark):
    a = generators.recursive_matrix(spark, 6, 4).edges.agg(F.sum(F.hash("u", "v"))).first()[0]
    spark.conf.set("spark.sql.shuffle.partitions", "7")
    b = generators.recursive_matrix(spark, 6, 4).edges.agg(F.sum(F.hash("u", "v"))).first()[0]
    spark.conf.set("spark.sql.shuffle.partitions", "4")
    assert a == b
