"""Coverage and modularity of a partition, from community statistics in whole numbers."""

from __future__ import annotations

from dataclasses import replace

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shoal.core.graph import Graph


def community_stats(g: Graph, assignment: DataFrame) -> DataFrame:
    """(comm, size, vol, inner_w, cut_w): vol = 2 inner_w + cut_w."""
    zero = F.lit(0).cast("long")
    twins = g.held_twins
    if twins is not None:
        small = replace(twins, members=twins.grouped(assignment))
        vol = small.members.join(twins.volumes, "cls").groupBy(F.col("id").alias("comm")).agg(F.sum(F.col("k") * F.col("vol")).alias("vol"))
        inner = small.loops.withColumnRenamed("id", "comm")
        rows = assignment.groupBy("comm").agg(F.count("*").alias("size")).join(vol, "comm", "left").join(inner, "comm", "left")
        rows = rows.select("comm", "size", F.coalesce("vol", zero).alias("vol"), F.coalesce("loop_w", zero).alias("inner_w"))
        return rows.withColumn("cut_w", F.col("vol") - 2 * F.col("inner_w"))
    labels = g.parts.labels(assignment) if g.parts is not None else None
    if labels is not None:
        comm, size, vol, inner = g.parts.communities(labels)
        rows = g.spark.createDataFrame(pa.table({"comm": comm, "size": size, "vol": vol, "inner_w": inner}), "comm long, size long, vol long, inner_w long")
        return rows.withColumn("cut_w", F.col("vol") - 2 * F.col("inner_w"))
    a, b = assignment.select(F.col("id").alias("u"), F.col("comm").alias("cu")), assignment.select(F.col("id").alias("v"), F.col("comm").alias("cv"))
    ends = g.edges.join(a, "u").join(b, "v")
    inside = F.col("cu") == F.col("cv")
    rows = ends.select(F.inline(F.array(F.struct(F.col("cu").alias("comm"), F.when(inside, F.col("w")).otherwise(zero).alias("inner_w"), F.when(~inside, F.col("w")).otherwise(zero).alias("cut_w")), F.struct(F.col("cv").alias("comm"), zero.alias("inner_w"), F.when(~inside, F.col("w")).otherwise(zero).alias("cut_w")))))
    sums = rows.groupBy("comm").agg(F.sum("inner_w").alias("inner_w"), F.sum("cut_w").alias("cut_w"))
    sizes = assignment.groupBy("comm").agg(F.count("*").alias("size"))
    return sizes.join(sums, "comm", "left").select("comm", "size", (2 * F.coalesce("inner_w", zero) + F.coalesce("cut_w", zero)).alias("vol"), F.coalesce("inner_w", zero).alias("inner_w"), F.coalesce("cut_w", zero).alias("cut_w"))


def coverage(g: Graph, assignment: DataFrame) -> DataFrame:
    """One row (inner_w, total_w, coverage)."""
    a, b = assignment.select(F.col("id").alias("u"), F.col("comm").alias("cu")), assignment.select(F.col("id").alias("v"), F.col("comm").alias("cv"))
    sums = g.edges.join(a, "u").join(b, "v").agg(F.sum(F.when(F.col("cu") == F.col("cv"), F.col("w")).otherwise(0)).alias("inner_w"), F.sum("w").alias("total_w"))
    return sums.select("inner_w", "total_w", F.round(F.col("inner_w").cast("double") / F.col("total_w").cast("double"), 6).alias("coverage"))


def modularity_terms(g: Graph, assignment: DataFrame, total: int, gamma: int | tuple[int, int] = 1) -> DataFrame:
    """(comm, size, vol, inner_w, term): each community's share of the modularity."""
    p, q = gamma if isinstance(gamma, tuple) else (gamma, 1)
    share = F.col("vol").cast("double") / F.lit(2.0 * total)
    return community_stats(g, assignment).select("comm", "size", "vol", "inner_w", F.round(F.col("inner_w").cast("double") / F.lit(float(total)) - F.lit(p / q) * share * share, 9).alias("term"))


def modularity(g: Graph, assignment: DataFrame, gamma: int | tuple[int, int] = 1, total: int | None = None) -> DataFrame:
    """One row (communities, modularity). The sum of squared volumes is exact before the one division."""
    p, q = gamma if isinstance(gamma, tuple) else (gamma, 1)
    s = community_stats(g, assignment)
    vol = F.col("vol").cast("decimal(19,0)")
    sums = s.agg(F.count("*").alias("communities"), F.sum("inner_w").cast("double").alias("inner_w"), F.sum("vol").cast("double").alias("whole"), F.sum((vol * vol).cast("decimal(38,0)")).cast("double").alias("squares"))
    return sums.select("communities", F.round(2 * F.col("inner_w") / F.col("whole") - F.lit(p / q) * F.col("squares") / (F.col("whole") * F.col("whole")), 6).alias("modularity"))


def community_sizes(assignment: DataFrame) -> DataFrame:
    return assignment.groupBy("comm").agg(F.count("*").alias("size"))


def size_histogram(assignment: DataFrame) -> DataFrame:
    return community_sizes(assignment).groupBy("size").agg(F.count("*").alias("communities"))


def contested_edges(g: Graph, runs: DataFrame) -> DataFrame:
    """Edges inside a community in some runs and between communities in others: (u, v, w, inside_runs, runs)."""
    a, b = runs.select("run", F.col("id").alias("u"), F.col("comm").alias("cu")), runs.select("run", F.col("id").alias("v"), F.col("comm").alias("cv"))
    both = g.edges.where("u <> v").join(a, "u").join(b, ["run", "v"])
    votes = both.groupBy("u", "v", "w").agg(F.sum((F.col("cu") == F.col("cv")).cast("long")).alias("inside_runs"), F.count("*").alias("runs"))
    return votes.where("inside_runs > 0 AND inside_runs < runs").select("u", "v", "w", "inside_runs", "runs")
