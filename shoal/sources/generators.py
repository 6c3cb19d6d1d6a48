"""Synthetic graphs on spark.range, by seeded arithmetic: the same for any number of partitions.

Some take their nodes, or the numbers that draw their edges, from a given table instead: one a row of `nodes(id)`
(dense ids from 0 where said so) or `draws(id)`."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from shoal.core.graph import Graph, index_nodes


def _unit(*parts: Column | int) -> Column:
    """A number in [0, 1) from a hash."""
    cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    return F.pmod(F.xxhash64(*cols), F.lit(1 << 53)).cast("double") / float(1 << 53)


def _nodes(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select("id")


def dense(rows: DataFrame, column: str) -> DataFrame:
    """(id) from 0, one a distinct value of the column."""
    return index_nodes(rows, column).select("id")


def ring_of_cliques(spark: SparkSession, cliques: int, size: int) -> Graph:
    rows = spark.range(cliques * size * size).select((F.col("id") / (size * size)).cast("long").alias("c"), ((F.col("id") / size).cast("long") % size).alias("a"), (F.col("id") % size).alias("b"))
    inner = rows.where("a < b").select((F.col("c") * size + F.col("a")).alias("u"), (F.col("c") * size + F.col("b")).alias("v"), F.lit(1).alias("w"))
    ring = spark.range(cliques).select((F.col("id") * size).alias("u"), ((F.col("id") + 1) % cliques * size + 1).alias("v"), F.lit(1).alias("w"))
    return Graph.of(inner.union(ring), _nodes(spark, cliques * size))


def star(spark: SparkSession, leaves: int) -> Graph:
    return Graph.of(spark.range(1, leaves + 1).select(F.lit(0).alias("u"), F.col("id").alias("v"), F.lit(1).alias("w")))


def path(spark: SparkSession, n: int) -> Graph:
    return Graph.of(spark.range(n - 1).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"), F.lit(1).alias("w")), _nodes(spark, n))


def cycle(spark: SparkSession, n: int) -> Graph:
    return Graph.of(spark.range(n).select(F.col("id").alias("u"), ((F.col("id") + 1) % n).alias("v"), F.lit(1).alias("w")))


def grid(spark: SparkSession, rows: int, cols: int) -> Graph:
    cell = spark.range(rows * cols)
    right = cell.where(F.col("id") % cols < cols - 1).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"), F.lit(1).alias("w"))
    down = cell.where(F.col("id") < (rows - 1) * cols).select(F.col("id").alias("u"), (F.col("id") + cols).alias("v"), F.lit(1).alias("w"))
    return Graph.of(right.union(down), cell.select("id"))


def biclique(spark: SparkSession, a: int, b: int) -> Graph:
    return Graph.of(spark.range(a * b).select((F.col("id") % a).alias("u"), ((F.col("id") / a).cast("long") + a).alias("v"), F.lit(1).alias("w")))


def two_density(spark: SparkSession, n: int, groups: int, p_in: float, p_out: float, seed: int = 0, nodes: DataFrame | None = None, draws: DataFrame | None = None) -> tuple[Graph, DataFrame]:
    """Groups with dense insides and sparse betweens. Edges are drawn by number (expected counts), so the work is
    that of the edges, not of the pairs; repeated draws fall together. Given `draws` (for n dense `nodes`), each draws
    one edge, inside as often as that is expected. Truth: id % groups."""
    size = n // groups
    inside, between = round(groups * size * (size - 1) / 2 * p_in), round((n * (n - 1) / 2 - groups * size * (size - 1) / 2) * p_out)
    pick = lambda m, tag: (_unit(F.col("id"), seed, tag) * m).cast("long")
    if draws is None:
        first, second = spark.range(inside), spark.range(between)
    else:
        near = _unit(F.col("id"), seed, 5) < inside / max(1, inside + between)
        first, second = draws.where(near), draws.where(~near)
    a = first.select((pick(size, 1) * groups + pick(groups, 0)).alias("u"), (pick(size, 2) * groups + pick(groups, 0)).alias("v"))
    b = second.select(pick(n, 3).alias("u"), pick(n, 4).alias("v")).where(F.col("u") % groups != F.col("v") % groups)
    edges = a.union(b).where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct().withColumn("w", F.lit(1))
    nodes = _nodes(spark, n) if nodes is None else nodes
    return Graph.of(edges, nodes), nodes.select("id", (F.col("id") % groups).alias("comm"))


def planted_heavy_tail(spark: SparkSession, n: int, mixing: float, degree_exponent: float = 2.5, size_exponent: float = 1.5, least_degree: int = 10, most_degree: int = 50, least_size: int = 20, most_size: int = 100, seed: int = 0, given: DataFrame | None = None) -> tuple[Graph, DataFrame]:
    """Power-law degrees and community sizes. A node's stubs draw partners inside its community or, with
    probability `mixing`, anywhere. `given`: the n nodes, dense ids. Truth: the community."""
    power = lambda u, low, high, e: F.pow(F.lit(low ** (1 - e)) + u * F.lit(high ** (1 - e) - low ** (1 - e)), F.lit(1 / (1 - e)))
    # communities are consecutive ranges of nodes; a size is drawn per community, and the sizes' running sum places them
    k = math.ceil(2 * n / least_size)
    sizes = [int(r["s"]) for r in spark.range(k).select(power(_unit(F.col("id"), seed, 11), least_size, most_size, size_exponent).cast("long").alias("s"), "id").orderBy("id").collect()] if n <= 10_000_000 else None
    if sizes is None:
        raise ValueError("more than 10 million nodes: community sizes would not fit the driver")
    bounds, at = [], 0
    for s in sizes:
        if at >= n:
            break
        bounds.append((at, min(s, n - at)))
        at += s
    groups = spark.createDataFrame(bounds, "start long, size long")
    nodes = groups.select(F.explode(F.sequence("start", F.col("start") + F.col("size") - 1)).alias("id"), "start", "size")
    if given is not None:
        nodes = given.join(nodes, "id")
    stubs = nodes.select("id", "start", "size", F.explode(F.sequence(F.lit(1), (power(_unit(F.col("id"), seed, 12), least_degree, most_degree, degree_exponent) / 2).cast("int") + 1)).alias("k"))
    out = _unit(F.col("id"), F.col("k"), seed, 13) < mixing
    u = _unit(F.col("id"), F.col("k"), seed, 14)
    other = F.when(out, (u * n).cast("long")).otherwise(F.col("start") + (u * F.col("size")).cast("long"))
    edges = stubs.select("id", other.alias("o")).where("id <> o").select(F.least("id", "o").alias("u"), F.greatest("id", "o").alias("v")).distinct().withColumn("w", F.lit(1))
    return Graph.of(edges, nodes.select("id")), nodes.select("id", F.col("start").alias("comm"))


def recursive_matrix(spark: SparkSession, scale: int, edge_factor: int = 16, a: float = 0.57, b: float = 0.19, c: float = 0.19, seed: int = 0, draws: DataFrame | None = None) -> Graph:
    """Edges that fall into quadrants of the adjacency matrix, one bit of both ends a level; `draws` in place of edge_factor a node."""
    # higher-order functions keep the generated code small; one long expression a level of both ends is not compiled
    r = F.transform(F.sequence(F.lit(0), F.lit(scale - 1)), lambda level: _unit(F.col("id"), seed, level))
    bit = lambda x: x.cast("long")
    u = F.aggregate("r", F.lit(0).cast("long"), lambda n, x: n * 2 + bit(x >= a + b))
    v = F.aggregate("r", F.lit(0).cast("long"), lambda n, x: n * 2 + bit(((x >= a) & (x < a + b)) | (x >= a + b + c)))
    draws = spark.range(edge_factor << scale) if draws is None else draws
    edges = draws.select(r.alias("r")).select(u.alias("u"), v.alias("v")).where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct().withColumn("w", F.lit(1))
    return Graph.of(edges, _nodes(spark, 1 << scale))


def hyperbolic_disk(spark: SparkSession, n: int, degree: float = 8.0, alpha: float = 0.75, bands: int = 0, seed: int = 0, nodes: DataFrame | None = None) -> Graph:
    """Points on a hyperbolic disk, joined when closer than its radius. Points lie in rings of radius; for each
    pair of rings the largest angle that can still join them bounds an interval join on angle cells. `nodes`: the n points, any distinct ids."""
    xi = alpha / (alpha - 0.5)
    radius = 2 * math.log(8 * n * xi * xi / (math.pi * 2 * degree) / 4 * 2) if degree > 0 else 2 * math.log(n)
    rings = bands or max(4, int(radius))
    r = F.acosh(1 + (math.cosh(alpha * radius) - 1) * _unit(F.col("id"), seed, 21)) / alpha
    points = (spark.range(n) if nodes is None else nodes).select("id", r.alias("r"), (_unit(F.col("id"), seed, 22) * 2 * math.pi).alias("t"))
    points = points.withColumn("ring", F.least(F.lit(rings - 1), (F.col("r") / (radius / rings)).cast("int")))
    pairs = []
    for i in range(rings):
        for j in range(i, rings):
            low_i, low_j = i * radius / rings, j * radius / rings
            if low_i + low_j < radius or low_i == 0:
                width = math.pi
            else:
                x = (math.cosh(low_i) * math.cosh(low_j) - math.cosh(radius)) / (math.sinh(low_i) * math.sinh(low_j))
                width = math.acos(max(-1.0, min(1.0, x)))
            cells = max(1, min(1 << 20, int(2 * math.pi / max(width, 1e-9))))
            pairs.append((i, j, cells))
    plan = spark.createDataFrame(pairs, "ri int, rj int, cells int")
    cell = lambda c: (F.col("t") / (2 * math.pi) * c).cast("long")
    inner = points.join(F.broadcast(plan), F.col("ring") == F.col("ri")).select("ri", "rj", "cells", F.col("id").alias("a"), F.col("r").alias("ra"), F.col("t").alias("ta"), F.explode(F.array_distinct(F.transform(F.array(F.lit(-1), F.lit(0), F.lit(1)), lambda d: F.pmod(cell(F.col("cells")) + d, F.col("cells"))))).alias("cell"))
    outer = points.join(F.broadcast(plan), F.col("ring") == F.col("rj")).select("ri", "rj", F.col("id").alias("b"), F.col("r").alias("rb"), F.col("t").alias("tb"), cell(F.col("cells")).alias("cell"))
    both = inner.join(outer, ["ri", "rj", "cell"]).where("ri < rj OR a < b")
    gap = F.lit(math.pi) - F.abs(F.lit(math.pi) - F.abs(F.col("ta") - F.col("tb")))
    near = F.cosh("ra") * F.cosh("rb") - F.sinh("ra") * F.sinh("rb") * F.cos(gap) <= math.cosh(radius)
    edges = both.where(near).where("a <> b").select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).distinct().withColumn("w", F.lit(1))
    return Graph.of(edges, points.select("id"))
