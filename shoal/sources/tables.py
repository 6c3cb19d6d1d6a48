"""Readers and writers: the given tables, edge lists, adjacency lines, and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shoal.core.graph import Graph


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", sep: str = ",") -> Graph:
    """An edge list u, v[, w]; missing weights are 1."""
    if fmt == "csv":
        rows = spark.read.csv(path, sep=sep, comment="#").selectExpr("*")
        rows = rows.toDF(*["u", "v", "w"][: len(rows.columns)])
    else:
        rows = spark.read.format(fmt).load(path)
    if "w" not in rows.columns:
        rows = rows.withColumn("w", F.lit(1))
    return Graph.of(rows.selectExpr("CAST(u AS BIGINT) u", "CAST(v AS BIGINT) v", "CAST(w AS BIGINT) w"))


def read_adjacency_lines(spark: SparkSession, path: str) -> Graph:
    """Text of one node a line, 'id: neighbour neighbour ...'; each edge may stand on one or on both of its ends' lines."""
    lines = spark.read.text(path).where("value LIKE '%:%'").select(F.split("value", ":").alias("p"))
    rows = lines.select(F.trim(F.col("p")[0]).cast("long").alias("a"), F.explode_outer(F.filter(F.split(F.trim(F.col("p")[1]), r"\s+"), lambda x: x != "").cast("array<bigint>")).alias("b"))
    edges = rows.where("b IS NOT NULL").select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).distinct().withColumn("w", F.lit(1))
    return Graph.of(edges, rows.select(F.col("a").alias("id")).distinct())


def write_graph(g: Graph, path: str) -> None:
    g.edges.write.mode("overwrite").parquet(f"{path}/edges")
    g.nodes.write.mode("overwrite").parquet(f"{path}/nodes")


def read_graph(spark: SparkSession, path: str) -> Graph:
    return Graph(spark.read.parquet(f"{path}/edges"), spark.read.parquet(f"{path}/nodes"))


def write_assignment(assignment: DataFrame, table: str, buckets: int = 16) -> None:
    """A table bucketed by node, so later joins on the node need no shuffle of it."""
    assignment.write.mode("overwrite").bucketBy(buckets, "id").sortBy("id").saveAsTable(table)


def append_metrics(metrics: DataFrame, path: str) -> None:
    metrics.write.mode("append").json(path)


def export_community_graph(g: Graph, sizes: DataFrame, path: str) -> None:
    g.edges.write.mode("overwrite").option("header", True).csv(f"{path}/edges")
    sizes.write.mode("overwrite").option("header", True).csv(f"{path}/nodes")
