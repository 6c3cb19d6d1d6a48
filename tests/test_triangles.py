"""Triangles against brute force, with several parts, and what their plan sends through the shuffle."""

import itertools
import random

from pyspark.sql import functions as F

from shoal.core.graph import Graph
from shoal.experiments import stage_costs
from shoal.measures import profile


def test_triangles_of_a_random_graph(spark, monkeypatch):
    monkeypatch.setattr(profile, "TRIANGLE_EDGES", 20, raising=False)
    monkeypatch.setattr(profile, "WEDGES", 50, raising=False)
    rng = random.Random(5)
    pairs = {p for p in itertools.combinations(range(40), 2) if rng.random() < 0.35}
    want: dict[int, int] = {}
    for x, y, z in itertools.combinations(range(40), 3):
        if {(x, y), (x, z), (y, z)} <= pairs:
            for i in (x, y, z):
                want[i] = want.get(i, 0) + 1
    g = Graph.of(spark.createDataFrame([(*p, 1) for p in pairs] + [(3, 3, 1)], "u long, v long, w long"))
    assert {r["id"]: r["triangles"] for r in profile.triangles(g).collect()} == want


def test_wedges_are_not_shuffled(spark):
    """A complete graph of 200 nodes has 1.3 million wedges and 20 thousand edges; like a large graph's, they are not broadcast."""
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        _complete(spark)
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def _complete(spark):
    nodes = spark.range(200)
    edges = nodes.toDF("u").crossJoin(nodes.toDF("v")).where("u < v").withColumn("w", F.lit(1).cast("long"))
    found = {}
    cost = stage_costs(spark, lambda: found.update({r["id"]: r["triangles"] for r in profile.triangles(Graph(edges, nodes)).collect()}))
    assert found == dict.fromkeys(range(200), 199 * 198 // 2)
    assert cost["shuffle_mb"] < 2
