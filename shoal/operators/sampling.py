"""Deterministic samples of a graph: what is kept depends on ids and a seed only, never on partitioning."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shoal.core.graph import Graph

_PRIME, _FACTOR = 2147483647, 48271


def kept(key: Column, permille: int, seed: int = 0) -> Column:
    """Whether a whole number of 0 or more falls into the kept thousandths."""
    return (((key % _PRIME) * _FACTOR + seed) % _PRIME) % 1000 < permille


def _edge_key(a: str, b: str) -> Column:
    return (F.col(a) % 1000003) * 1009 + F.col(b) % 1000003


def sample_nodes(g: Graph, permille: int, seed: int = 0) -> Graph:
    """The kept nodes and the edges among them; a filter on both ends, without a join."""
    return Graph(g.edges.where(kept(F.col("u"), permille, seed) & kept(F.col("v"), permille, seed)), g.nodes.where(kept(F.col("id"), permille, seed)))


def sample_edges(g: Graph, permille: int, seed: int = 0) -> Graph:
    """The kept edges and all nodes."""
    return Graph(g.edges.where(kept(_edge_key("u", "v"), permille, seed)), g.nodes)


def spread_from(g: Graph, seeds: DataFrame, hops: int, permille: int, seed: int = 0) -> DataFrame:
    """(id, hop): nodes that a fire from the seeds reaches, which crosses each arc with the given chance; the first hop counts.

    Only the front is joined with the arcs, whose chance is drawn in the scan."""
    arcs = g.arcs.where(kept(_edge_key("src", "dst"), permille, seed)).select("src", "dst")
    reached = seeds.select("id", F.lit(0).alias("hop")).distinct()
    front = reached
    for hop in range(1, hops + 1):
        near = arcs.join(front.select(F.col("id").alias("src")), "src", "left_semi").select(F.col("dst").alias("id")).distinct()
        front = near.join(reached, "id", "left_anti").select("id", F.lit(hop).alias("hop"))
        reached = reached.union(front)
    return reached
