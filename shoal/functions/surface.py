"""Graphs and communities for SQL: temporary views and a table function over adjacency lines."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from shoal.core.graph import Graph


def publish(spark: SparkSession, name: str, g: Graph, assignment: DataFrame | None = None) -> list[str]:
    """Registers `name`_edges, `name`_nodes and, if given, `name`_communities; returns the views' names."""
    views = {f"{name}_edges": g.edges, f"{name}_nodes": g.nodes}
    if assignment is not None:
        views[f"{name}_communities"] = assignment
    for view, rows in views.items():
        rows.createOrReplaceTempView(view)
    return list(views)


class _Adjacency:
    """Rows (u, v) of a line 'id: neighbour neighbour ...'. A line without a colon, or null, has none."""

    def eval(self, line: str) -> Iterator[tuple[int, int]]:
        node, colon, others = (line or "").partition(":")
        if colon and node.strip():
            for other in others.split():
                yield int(node), int(other)


def register_functions(spark: SparkSession) -> None:
    """explode_adjacency(line), to be used as a lateral table in SQL."""
    spark.udtf.register("explode_adjacency", udtf(_Adjacency, returnType="u bigint, v bigint"))
