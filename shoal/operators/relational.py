"""What users do before and after detection: cut, attach, rank, roll up, compare snapshots, join in time."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from shoal.core.graph import Graph


def _ends(g: Graph, assignment: DataFrame) -> DataFrame:
    a, b = assignment.select(F.col("id").alias("u"), F.col("comm").alias("cu")), assignment.select(F.col("id").alias("v"), F.col("comm").alias("cv"))
    return g.edges.join(a, "u").join(b, "v")


def cut_edges(g: Graph, assignment: DataFrame) -> DataFrame:
    """Edges between communities: (u, v, w, cu, cv)."""
    return _ends(g, assignment).where("cu <> cv").select("u", "v", "w", "cu", "cv")


def edges_within(g: Graph, assignment: DataFrame) -> DataFrame:
    return _ends(g, assignment).where("cu = cv").select("u", "v", "w", F.col("cu").alias("comm"))


def heaviest_cut(g: Graph, assignment: DataFrame, k: int) -> DataFrame:
    return cut_edges(g, assignment).orderBy(F.desc("w"), "u", "v").limit(k)


def ego_net(g: Graph, node: int, hops: int = 1) -> DataFrame:
    """Edges among a node and all nodes within so many steps."""
    near = g.nodes.where(F.col("id") == node)
    for _ in range(hops):
        near = near.union(g.arcs.join(near.withColumnRenamed("id", "src"), "src", "left_semi").select(F.col("dst").alias("id"))).distinct()
    return g.edges.join(near.withColumnRenamed("id", "u"), "u", "left_semi").join(near.withColumnRenamed("id", "v"), "v", "left_semi").select("u", "v", "w")


def unassigned(g: Graph, assignment: DataFrame) -> DataFrame:
    return g.nodes.join(assignment, "id", "left_anti")


def attach(assignment: DataFrame, rows: DataFrame, key: str) -> DataFrame:
    """Adds comm to any table by its key."""
    return rows.join(assignment.select(F.col("id").alias(key), "comm"), key)


def top_members(g: Graph, assignment: DataFrame, k: int) -> DataFrame:
    """(comm, id, vol, place): the k members of largest volume in each community."""
    rows = assignment.join(g.node_stats.select("id", "vol"), "id")
    place = F.row_number().over(Window.partitionBy("comm").orderBy(F.desc("vol"), "id"))
    return rows.withColumn("place", place).where(F.col("place") <= k).select("comm", "id", "vol", "place")


def size_share(assignment: DataFrame) -> DataFrame:
    """(comm, size, running share) from the largest down; communities only, so the window holds few rows."""
    sizes = assignment.groupBy("comm").agg(F.count("*").alias("size"))
    w = Window.orderBy(F.desc("size"), "comm")
    run = F.sum("size").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return sizes.select("comm", "size", F.round(run / F.sum("size").over(Window.partitionBy()), 6).alias("share"))


def grouped(rows: DataFrame, keys: list[str], measure: Column, how: str = "rollup") -> DataFrame:
    """Subtotals of a measure over rollup or cube of the keys, with counts."""
    return getattr(rows, how)(*keys).agg(F.count("*").alias("n"), measure.alias("total"))


def community_profile(assignment: DataFrame, rows: DataFrame, key: str, value: str) -> DataFrame:
    return attach(assignment, rows, key).groupBy("comm").agg(F.count("*").alias("n"), F.sum(value).alias("total"), F.min(value).alias("least"), F.max(value).alias("most"), F.count_distinct(key).alias("members"))


def asof_community(events: DataFrame, snapshots: DataFrame) -> DataFrame:
    """(event_id, user_id, comm): the community in the newest snapshot at or before each event. A union and one
    window by user instead of an inequality join."""
    a = events.select("event_id", "user_id", "ts", F.lit(None).cast("long").alias("comm"), F.lit(1).alias("o"))
    b = snapshots.select(F.lit(None).cast("long").alias("event_id"), F.col("id").alias("user_id"), "ts", "comm", F.lit(0).alias("o"))
    last = F.last("comm", ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "o").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return a.unionByName(b).withColumn("comm", last).where("event_id IS NOT NULL").select("event_id", "user_id", "comm")


def interval_edges(events: DataFrame, seconds: int) -> DataFrame:
    """(u, v, w): pairs of users with events of one type at most so many seconds apart; w counts pairs of events.
    Time is cut into cells of that length: a pair lies in one cell or in neighbouring ones."""
    e = events.select("user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t")).withColumn("cell", F.floor(F.col("t") / (seconds * 1_000_000)))
    left = e.select(F.col("user_id").alias("u"), F.col("event_type").alias("k"), F.col("t").alias("tu"), F.explode(F.array(F.col("cell") - 1, F.col("cell"), F.col("cell") + 1)).alias("cell"))
    right = e.select(F.col("user_id").alias("v"), F.col("event_type").alias("k"), F.col("t").alias("tv"), "cell")
    near = left.join(right, ["k", "cell"]).where((F.col("u") < F.col("v")) & (F.abs(F.col("tu") - F.col("tv")) <= seconds * 1_000_000))
    return near.groupBy("u", "v").agg(F.count("*").alias("w"))


def union_graphs(a: Graph, b: Graph) -> Graph:
    return Graph.of(a.edges.union(b.edges), a.nodes.union(b.nodes))


def common_edges(a: Graph, b: Graph) -> DataFrame:
    return a.edges.select("u", "v").intersect(b.edges.select("u", "v"))


def lost_edges(before: Graph, after: Graph) -> DataFrame:
    return before.edges.select("u", "v").exceptAll(after.edges.select("u", "v"))


def churn(snapshots: DataFrame) -> DataFrame:
    """(ts, moved): nodes whose community differs from the snapshot before."""
    was = F.lag("comm").over(Window.partitionBy("id").orderBy("ts"))
    return snapshots.withColumn("was", was).groupBy("ts").agg(F.count_if(F.col("was").isNotNull() & (F.col("was") != F.col("comm"))).alias("moved"))
