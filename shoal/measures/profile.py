"""Sizes, degrees, components and clustering of a graph."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shoal.core.components import star_labels
from shoal.core.graph import Graph
from shoal.core.storage import Scratch
from shoal.measures import triangles as placed

#: Edges of one pair of parts, about, and wedges that are closed at once.
TRIANGLE_EDGES, WEDGES = 50_000, 2_000_000


def degrees(g: Graph) -> DataFrame:
    d = g.arcs.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree"))
    return g.nodes.join(d, "id", "left").select("id", F.coalesce("degree", F.lit(0).cast("long")).alias("degree"))


def degree_profile(g: Graph) -> DataFrame:
    """(degree, nodes)."""
    return degrees(g).groupBy("degree").agg(F.count("*").alias("nodes"))


def connected_components(g: Graph) -> DataFrame:
    """(id, comm): each component named by its smallest node."""
    labels = star_labels(g.edges.select("u", "v"), Scratch(g.spark, "components"))
    return g.nodes.join(labels, "id", "left").select("id", F.coalesce("label", "id").alias("comm"))


def triangles(g: Graph) -> DataFrame:
    """(id, triangles): by arrays (`triangles.count`) where the driver can number the nodes, else by triples of parts."""
    return placed.count(g) if g.nodes.count() <= placed.PLACED else triangles_by_triples(g)


def triangles_by_triples(g: Graph) -> DataFrame:
    """(id, triangles). Nodes are dealt into parts; a task gets the edges between the parts of one triple, so an edge
    travels `parts` times and wedges are only held, a block at a time, where they are closed."""
    scratch = Scratch(g.spark, "triangles")
    edges = scratch.write(g.edges.where("u <> v").select("u", "v"))
    parts = max(2, math.ceil((edges.count() / TRIANGLE_EDGES) ** 0.5))
    part = lambda c: F.pmod(F.xxhash64(c, F.lit(7)), F.lit(parts)).cast("int")
    thirds = F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))
    dealt = edges.select("u", "v", part("u").alias("pu"), part("v").alias("pv"), thirds.alias("pw"))
    triple = F.array_sort(F.array("pu", "pv", "pw"))
    keyed = dealt.select("u", "v", "pu", "pv", ((triple[0] * parts + triple[1]).cast("long") * parts + triple[2]).alias("triple"))
    dealt = keyed.repartition("triple").sortWithinPartitions("triple")
    found = dealt.select("triple", "u", "v", "pu", "pv").mapInArrow(lambda batches: _closed(batches, parts), "id long, n long")
    return found.groupBy("id").agg(F.sum("n").alias("triangles"))


def _closed(batches: Iterator[pa.RecordBatch], parts: int) -> Iterator[pa.RecordBatch]:
    """Triangles at each node, one triple's edges after the other."""
    at, held = None, []

    def done() -> Iterator[pa.RecordBatch]:
        if held:
            ids, n = _count_triangles(*(np.concatenate(c) for c in zip(*held, strict=True)), at, parts)
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(n)], ["id", "n"])

    for b in batches:
        key, *columns = (c.to_numpy(zero_copy_only=False) for c in b.columns)
        cuts = np.flatnonzero(np.append(True, key[1:] != key[:-1])) if len(key) else np.zeros(0, np.int64)
        for low, high in zip(cuts.tolist(), [*cuts[1:].tolist(), len(key)], strict=False):
            if key[low] != at:
                yield from done()
                at, held = int(key[low]), []
            held.append([c[low:high] for c in columns])
    yield from done()


def _count_triangles(u: np.ndarray, v: np.ndarray, pu: np.ndarray, pv: np.ndarray, triple: int, parts: int) -> tuple[np.ndarray, np.ndarray]:
    """(id, triangles) of those whose nodes lie in the triple's parts, each edge from its end of lower (degree, place)."""
    ids, place = np.unique(np.concatenate([u, v]), return_inverse=True)
    part = np.zeros(len(ids), np.int64)
    part[place] = np.concatenate([pu, pv])
    n = len(ids)
    degree = np.bincount(place, minlength=n)
    rank = np.empty(n, np.int64)
    rank[np.argsort(degree, kind="stable")] = np.arange(n)
    x, y = rank[place[: len(u)]], rank[place[len(u) :]]
    code = np.unique(np.minimum(x, y) * n + np.maximum(x, y))
    a, b = code // n, code % n
    last = np.searchsorted(a, a, side="right")
    more = last - np.arange(len(a)) - 1  # later ends of the same node: wedges of each edge
    ends = np.cumsum(more)
    by_rank = np.empty(n, np.int64)
    by_rank[rank] = part
    out = np.zeros(n, np.int64)
    low = 0
    while low < len(a):
        high = max(low + 1, int(np.searchsorted(ends, (ends[low - 1] if low else 0) + WEDGES, side="right")))
        first = np.repeat(np.arange(low, high), more[low:high])
        second = first + 1 + np.arange(len(first)) - np.repeat(np.cumsum(more[low:high]) - more[low:high], more[low:high])
        want = b[first] * n + b[second]
        spot = np.minimum(np.searchsorted(code, want), len(code) - 1)
        hit = code[spot] == want
        corners = np.stack([a[first[hit]], b[first[hit]], b[second[hit]]])
        p = np.sort(by_rank[corners], axis=0)
        corners = corners[:, (p[0] * parts + p[1]) * parts + p[2] == triple]
        out += np.bincount(corners.ravel(), minlength=n)
        low = high
    some = out[rank]
    return ids[some > 0], some[some > 0]


def local_clustering(g: Graph) -> DataFrame:
    """(id, degree, triangles, clustering): 0 below degree 2."""
    rows = degrees(g).join(triangles(g), "id", "left").select("id", "degree", F.coalesce("triangles", F.lit(0).cast("long")).alias("triangles"))
    possible = F.col("degree") * (F.col("degree") - 1) / 2
    return rows.withColumn("clustering", F.round(F.when(F.col("degree") < 2, 0.0).otherwise(F.col("triangles") / possible), 6))


def profile(g: Graph) -> DataFrame:
    """One row (n, m, max_degree, components, lcc)."""
    c = local_clustering(g).agg(F.count("*").alias("n"), F.max("degree").alias("max_degree"), F.round(F.avg("clustering"), 4).alias("lcc"))
    m = g.edges.where("u <> v").agg(F.count("*").alias("m"))
    k = connected_components(g).agg(F.count_distinct("comm").alias("components"))
    return c.join(m).join(k).select("n", "m", "max_degree", "components", "lcc")  # single rows
