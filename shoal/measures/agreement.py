"""How far two partitions of the same nodes agree."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shoal.core.graph import Graph


def edge_rand(g: Graph, first: DataFrame, second: DataFrame) -> DataFrame:
    """Share of edges (loops apart) that both partitions put inside, or both between, communities."""
    labels = [g.parts.labels(x) for x in (first, second)] if g.parts is not None else [None]
    if all(x is not None for x in labels):
        sums = g.spark.createDataFrame([g.parts.agreeing(*labels)], "agree long, edges long")
        return sums.select("agree", "edges", F.round(F.col("agree").cast("double") / F.col("edges"), 6).alias("edge_rand"))
    both = first.select("id", F.col("comm").alias("x")).join(second.select("id", F.col("comm").alias("y")), "id")
    a, b = both.select(F.col("id").alias("u"), F.col("x").alias("xu"), F.col("y").alias("yu")), both.select(F.col("id").alias("v"), F.col("x").alias("xv"), F.col("y").alias("yv"))
    same = (F.col("xu") == F.col("xv")) == (F.col("yu") == F.col("yv"))
    sums = g.edges.where("u <> v").join(a, "u").join(b, "v").agg(F.count_if(same).alias("agree"), F.count("*").alias("edges"))
    return sums.select("agree", "edges", F.round(F.col("agree").cast("double") / F.col("edges"), 6).alias("edge_rand"))


def contingency(first: DataFrame, second: DataFrame) -> DataFrame:
    return first.select("id", F.col("comm").alias("x")).join(second.select("id", F.col("comm").alias("y")), "id").groupBy("x", "y").agg(F.count("*").alias("n"))


def _pairs(c):
    return (c * (c - 1) / 2).cast("double")


def pair_rand(first: DataFrame, second: DataFrame) -> DataFrame:
    """One row (pair_rand, adjusted_rand, nmi) from the contingency table: no table of node pairs."""
    t = contingency(first, second)
    joint = t.agg(F.sum(_pairs(F.col("n"))).alias("nij"), F.sum("n").alias("n"), F.sum(F.col("n") * F.log("n")).alias("hj"))
    rows = t.groupBy("x").agg(F.sum("n").alias("a")).agg(F.sum(_pairs(F.col("a"))).alias("ai"), F.sum(F.col("a") * F.log("a")).alias("hx"))
    cols = t.groupBy("y").agg(F.sum("n").alias("b")).agg(F.sum(_pairs(F.col("b"))).alias("bj"), F.sum(F.col("b") * F.log("b")).alias("hy"))
    one = joint.join(rows).join(cols)  # three single rows
    every = _pairs(F.col("n"))
    expected = F.col("ai") * F.col("bj") / every
    middle = (F.col("ai") + F.col("bj")) / 2
    n = F.col("n").cast("double")
    hx, hy = F.log(n) - F.col("hx") / n, F.log(n) - F.col("hy") / n
    mutual = F.log(n) + (F.col("hj") - F.col("hx") - F.col("hy")) / n
    return one.select(
        F.round((every + 2 * F.col("nij") - F.col("ai") - F.col("bj")) / every, 6).alias("pair_rand"),
        F.round(F.when(middle == expected, 1.0).otherwise((F.col("nij") - expected) / (middle - expected)), 6).alias("adjusted_rand"),
        F.round(F.when(hx + hy == 0, 1.0).otherwise(2 * mutual / (hx + hy)), 6).alias("nmi"),
    )
