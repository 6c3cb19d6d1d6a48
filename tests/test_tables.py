"""Readers, sinks and communities that follow a stream of edges."""

from pyspark.sql import functions as F

from shoal.core.graph import Graph
from shoal.operators.propagation import propagate_labels
from shoal.sources import tables
from shoal.streaming.edges import IncrementalCommunities, read_stream

EDGES = [(1, 2, 3), (1, 3, 1), (4, 5, 2)]


def _rows(df):
    return sorted(map(tuple, df.collect()))


def test_edge_lists(spark, tmp_path):
    (tmp_path / "e.csv").write_text("# u,v,w\n2,1,3\n1,3,1\n4,5,2\n")
    assert _rows(tables.read_edges(spark, f"{tmp_path}/e.csv").edges) == EDGES
    (tmp_path / "plain.csv").write_text("1 2\n2 1\n3 4\n")
    assert _rows(tables.read_edges(spark, f"{tmp_path}/plain.csv", sep=" ").edges.select("u", "v")) == [(1, 2), (3, 4)]


def test_adjacency_lines(spark, tmp_path):
    (tmp_path / "a.txt").write_text("1: 2 3\n2: 1\n3:\n7:\nno node\n")
    g = tables.read_adjacency_lines(spark, f"{tmp_path}/a.txt")
    assert _rows(g.edges) == [(1, 2, 1), (1, 3, 1)]
    assert _rows(g.nodes) == [(1,), (2,), (3,), (7,)]


def test_graph_round_trip(spark, tmp_path):
    g = Graph.of(spark.createDataFrame(EDGES, "u long, v long, w long"), spark.createDataFrame([(9,)], "id long"))
    tables.write_graph(g, f"{tmp_path}/g")
    back = tables.read_graph(spark, f"{tmp_path}/g")
    assert _rows(back.edges) == EDGES and _rows(back.nodes) == _rows(g.nodes)
    tables.append_metrics(spark.createDataFrame([("a", 1.5)], "name string, seconds double"), f"{tmp_path}/m")
    tables.append_metrics(spark.createDataFrame([("b", 2.5)], "name string, seconds double"), f"{tmp_path}/m")
    assert _rows(spark.read.json(f"{tmp_path}/m").select("name", "seconds")) == [("a", 1.5), ("b", 2.5)]


def test_communities_follow_a_stream(spark, tmp_path):
    """Two cliques that come in two files end as two communities; a node's later edges wake it."""
    clique = lambda ids: [(a, b, 1) for a in ids for b in ids if a < b]
    for part in (clique([1, 2, 3, 4]), clique([11, 12, 13, 14]) + [(4, 11, 1)]):
        spark.createDataFrame(part, "u long, v long, w long").coalesce(1).write.mode("append").parquet(f"{tmp_path}/edges")
    kept = IncrementalCommunities(spark)
    kept.follow(read_stream(spark, f"{tmp_path}/edges")).awaitTermination()
    assert _rows(kept.graph.nodes) == [(i,) for i in (1, 2, 3, 4, 11, 12, 13, 14)]
    groups = sorted(sorted(r["ids"]) for r in kept.labels.groupBy("comm").agg(F.collect_list("id").alias("ids")).collect())
    assert groups == [[1, 2, 3, 4], [11, 12, 13, 14]]
    whole = propagate_labels(kept.graph)
    assert whole.groupBy("comm").count().count() == 2
