"""Cost and quality scores of runs against a base method, and the Pareto frontier.

Input: rows (algo, graph, seconds, modularity).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def quality_vs_baseline(metrics: DataFrame, base: str = "base") -> DataFrame:
    """(algo, graph, time_ratio, modularity_delta) against the base method on the same graph."""
    b = metrics.where(F.col("algo") == base).select("graph", F.col("seconds").alias("bs"), F.col("modularity").alias("bq"))
    return metrics.join(b, "graph").select("algo", "graph", F.round(F.col("seconds") / F.col("bs"), 6).alias("time_ratio"), F.round(F.col("modularity") - F.col("bq"), 6).alias("modularity_delta"))


def scores(metrics: DataFrame, base: str = "base") -> DataFrame:
    """(algo, time_score, modularity_score): geometric mean of time ratios, mean of signed modularity differences."""
    b = metrics.where(F.col("algo") == base).select("graph", F.col("seconds").alias("bs"), F.col("modularity").alias("bq"))
    rows = metrics.join(b, "graph")
    return rows.groupBy("algo").agg(F.round(F.exp(F.avg(F.log(F.col("seconds") / F.col("bs")))), 4).alias("time_score"), F.round(F.avg(F.col("modularity") - F.col("bq")), 4).alias("modularity_score"))


def pareto(table: DataFrame) -> DataFrame:
    """Methods that no other beats in both scores. A handful of rows, hence the theta join."""
    other = table.select(F.col("time_score").alias("t"), F.col("modularity_score").alias("q"))
    beaten = (F.col("t") <= F.col("time_score")) & (F.col("q") >= F.col("modularity_score")) & ((F.col("t") < F.col("time_score")) | (F.col("q") > F.col("modularity_score")))
    return table.join(F.broadcast(other), beaten, "left_anti")


def edges_per_second(m: int, seconds: float) -> float:
    return m / seconds if seconds else float("inf")
