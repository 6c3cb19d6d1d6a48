"""Nearest vectors against all pairs in Spark's own arithmetic, with copies that tie across blocks."""

from pyspark.sql import functions as F

from shoal.functions.scalar import cosine
from shoal.graphs import builders


def test_neighbours_are_those_of_all_pairs(spark, monkeypatch):
    monkeypatch.setattr(builders, "KNN_BLOCK", 40, raising=False)
    unit = (F.pmod(F.xxhash64(F.col("id") % 60), F.lit(1000)) - 500).cast("float")  # 60 vectors, each 3 times or twice
    e = F.array(*(F.pmod(F.xxhash64(F.col("id") % 60, F.lit(d)), F.lit(1000)).cast("float") - 500 + unit / 7 for d in range(6))).cast("array<float>")
    vectors = spark.range(170).select(F.col("id").alias("vec_id"), e.alias("embedding")).persist()
    pairs = vectors.toDF("a", "x").crossJoin(vectors.toDF("b", "y")).where("a <> b").select("a", "b", cosine(F.col("x"), F.col("y")).alias("s")).collect()
    near: dict[int, list] = {}
    for r in pairs:
        near.setdefault(r["a"], []).append((-r["s"], r["b"]))
    want = {(min(a, b), max(a, b)) for a, some in near.items() for _, b in sorted(some)[:4]}
    found = builders.knn_graph(vectors, k=4)
    assert {(r["u"], r["v"]) for r in found.edges.collect()} == want
    assert found.nodes.count() == 170


def test_more_vectors_than_one_task_compares(spark):
    """Over 20,000 vectors raised an error."""
    e = F.array(F.cos(F.col("id") / 4000).cast("float"), F.sin(F.col("id") / 4000).cast("float"))
    g = builders.knn_graph(spark.range(20_500).select(F.col("id").alias("vec_id"), e.alias("embedding")), k=2)
    assert g.nodes.count() == 20_500
    assert g.edges.groupBy().agg(F.max(F.col("v") - F.col("u"))).first()[0] < 200


def test_missing_vectors_stand_alone(spark):
    rows = [(1, [1.0, 0.0]), (2, [1.0, 0.5]), (3, None), (4, [0.0, None])]
    g = builders.knn_graph(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), k=1)
    assert sorted(map(tuple, g.edges.collect())) == [(1, 2, 1)]
    assert g.nodes.count() == 4
