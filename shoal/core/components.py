"""Connected components by alternating star contraction.

Large star: each node sends its larger neighbours to the smallest of its neighbourhood; small star: it
sends its smaller ones there. Both keep the components and flatten them towards stars around the
smallest node, in a logarithmic number of rounds in practice. Every step is a sum-like aggregate
(minimum, combined before the shuffle) and an equi-join, so a hub is never gathered in one task.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from shoal.core.storage import Scratch

#: Edges that are handled in one task, and those a task of many holds at once.
SMALL, FOREST = 500_000, 1 << 20


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("k"), F.least("u", "m").alias("m"))
    return both.join(least, F.col("u") == F.col("k")).where("v > u AND v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(least.withColumnRenamed("u", "k"), F.col("u") == F.col("k")).where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).distinct()


def _settled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(id, label) for all edges (u, v) of one task: roots hook to smaller neighbours until no edge joins two of them."""
    held = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches]
    if not held:
        return
    u, v = (np.concatenate(x) for x in zip(*held, strict=True))
    ids, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    root = np.arange(len(ids))
    while len(a):
        x, y = root[a], root[b]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while (root[root] != root).any():
            root = root[root]
        apart = root[a] != root[b]
        a, b = a[apart], b[apart]
    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(ids[root])], ["id", "label"])


def _forests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges (u, v) that join the same nodes as all edges of one task, at most one a node: stars around the smallest."""
    held, size = [], 0
    for b in batches:
        held.append(b)
        size += b.num_rows
        if size >= FOREST:
            held = [pa.RecordBatch.from_arrays(x.columns, ["u", "v"]) for x in _settled(iter(held))]
            size = sum(b.num_rows for b in held) // 2  # a forest of many nodes is not cut down again and again
    for x in _settled(iter(held)):
        label = x.filter(pa.compute.not_equal(x.column(0), x.column(1)))
        yield pa.RecordBatch.from_arrays(label.columns, ["u", "v"])


def star_labels(edges: DataFrame, scratch: Scratch, max_rounds: int = 60) -> DataFrame:
    """(id, label) of every node that has an edge (u, v), label being the smallest id of its component."""
    seen = Observation()
    sums = (F.count("*").alias("n"), F.sum(F.hash("u", "v").cast("long")).alias("a"), F.sum(F.hash("v", "u").cast("long")).alias("b"))
    some = edges.where("u <> v").select(F.col("u").cast("long"), F.col("v").cast("long")).coalesce(2 * edges.sparkSession.sparkContext.defaultParallelism)
    now = scratch.write(some.mapInArrow(_forests, "u long, v long").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct().observe(seen, *sums))
    if seen.get["n"] <= SMALL:
        return scratch.write(now.coalesce(1).mapInArrow(_settled, "id long, label long"))
    mark = None
    for _ in range(max_rounds):
        seen = Observation()
        after = scratch.write(_small_star(_large_star(now)).observe(seen, *sums))
        sums_now = tuple(seen.get[k] for k in ("n", "a", "b"))
        scratch.drop(now)
        now = after
        if sums_now == mark:
            break
        mark = sums_now
    else:
        raise RuntimeError(f"components not settled after {max_rounds} rounds")
    return scratch.write(now.select(F.inline(F.array(F.struct(F.col("u").alias("id"), F.col("v").alias("label")), F.struct(F.col("v").alias("id"), F.col("v").alias("label"))))).distinct())
