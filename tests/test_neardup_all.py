"""The near-duplicate graph under the communities keeps large groups and all documents."""

from __future__ import annotations

from shoal.graphs import builders
from shoal.operators import propagation


def test_a_group_of_more_than_fifty_copies_stays_one_community(spark):
    rows = [(i, "one two three four five six seven") for i in range(60)] + [(100, "nothing in common with any of them"), (101, "short")]
    graph = builders.all_shared_shingles(spark.createDataFrame(rows, "doc_id long, text string"))
    assert graph.nodes.count() == 62
    assert {(r["u"], r["v"], r["w"]) for r in graph.edges.collect()} == {(0, i, 3) for i in range(1, 60)}
    found = {r["id"]: r["comm"] for r in propagation.propagate_labels(graph).collect()}
    assert len({found[i] for i in range(60)}) == 1 and len(found) == 62


def test_texts_are_cut_into_shingles_once(spark):
    """What reads the graph, however often, reads written edges: no plan on it goes back to the documents."""
    rows = [(i, f"one two three four five six {i % 3}") for i in range(9)] + [(20, None), (21, "one two three four five six 0")]
    graph = builders.all_shared_shingles(spark.createDataFrame(rows, "doc_id long, text string"))
    assert "md5" not in graph.arcs._jdf.queryExecution().optimizedPlan().toString()
    weights = {(r["u"], r["v"]): r["w"] for r in graph.edges.collect()}
    assert weights == {(u, v): 3 if u % 3 == v % 3 or (v == 21 and u % 3 == 0) else 2 for u in [*range(9)] for v in [*range(9), 21] if u < v}
