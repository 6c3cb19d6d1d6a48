"""Undirected weighted graphs as two DataFrames, and the partitions of their nodes.

`edges(u, v, w)`: one row an edge, u <= v, w > 0, loops allowed; `nodes(id)`: every node, isolated ones
included. Weights are whole numbers, so that sums and scores are exact and do not depend on the order of
rows. An assignment `(id, comm)` names every node's community; canonical names are the smallest member.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import cached_property

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from shoal.core.storage import Scratch

#: Classes, and cells of nodes times classes, up to which a graph is held by classes of equal nodes.
MAX_CLASSES, MAX_CELLS = 2_000, 1 << 25


@dataclass
class Twins:
    """A graph by classes of nodes with equal neighbours: members(id, cls, k), how many first nodes of a class a node holds
    (one, until it is contracted); between(a, b, w), the weight between two first nodes of classes a <= b, also a = b, or
    what makes it from the written members."""

    members: DataFrame
    between: DataFrame | Callable[[DataFrame], DataFrame]
    nodes: int = 0
    low: int = 0
    high: int = 0
    pairs: int = 0
    weight: int = 0

    @cached_property
    def held(self) -> Twins | None:
        """The same, written and counted; None where classes are too many or weights too large for `TwinGraph`."""
        if self.nodes:
            return self
        scratch = Scratch(self.members.sparkSession, "twins")
        members = scratch.write(self.members)
        n, low, high, classes = members.agg(F.count_distinct("id"), F.min("id"), F.max("id"), F.count_distinct("cls")).first()
        if not n or low < 0 or classes > MAX_CLASSES or n * classes > MAX_CELLS:
            return None
        if callable(self.between):
            between = scratch.write(self.between(members))
        else:
            between = self.between
        members = members.select("id", "cls", "k")
        number = members.groupBy("cls").agg(F.sum("k").cast("decimal(18,0)").alias("n"))
        a, b = number.toDF("a", "na"), number.toDF("b", "nb")
        pairs = F.when(F.col("a") == F.col("b"), F.col("na") * (F.col("nb") - 1) / 2).otherwise(F.col("na") * F.col("nb")).cast("decimal(28,0)")
        found = between.join(a, "a").join(b, "b").agg(F.sum(pairs).alias("p"), F.sum(pairs * F.col("w").cast("decimal(10,0)")).alias("w")).first()
        pairs, weight = int(found["p"] or 0), int(found["w"] or 0)
        return Twins(members, between, n, low, high, pairs, weight) if weight < 1 << 51 else None

    @property
    def arcs(self) -> DataFrame:
        """(a, b, w) in both directions."""
        return self.between.unionAll(self.between.where("a <> b").select("b", "a", "w"))

    @property
    def volumes(self) -> DataFrame:
        """(cls, vol): the volume of a first node of each class."""
        number = self.members.groupBy(F.col("cls").alias("b")).agg(F.sum("k").alias("n"))
        others = F.col("n") - F.when(F.col("a") == F.col("b"), 1).otherwise(0)
        return self.arcs.join(number, "b").groupBy(F.col("a").alias("cls")).agg(F.sum(F.col("w") * others).alias("vol"))

    def grouped(self, assignment: DataFrame) -> DataFrame:
        """The members of communities."""
        return self.members.join(assignment, "id").groupBy(F.col("comm").alias("id"), "cls").agg(F.sum("k").alias("k"))

    @property
    def loops(self) -> DataFrame:
        """(id, loop_w): the weight inside each node."""
        m, own = self.members, self.between.where("a = b").select(F.col("a").alias("cls"), F.col("w").alias("own"))
        pull = m.withColumnRenamed("cls", "a").join(self.arcs, "a").select("id", F.col("b").alias("cls"), (F.col("k") * F.col("w")).alias("pull"))
        twice = pull.join(m, ["id", "cls"]).groupBy("id").agg(F.sum(F.col("pull") * F.col("k")).alias("all"))
        selves = m.join(own, "cls").groupBy("id").agg(F.sum(F.col("k") * F.col("own")).alias("own"))
        return twice.join(selves, "id", "left").select("id", ((F.col("all") - F.coalesce("own", F.lit(0))) / 2).cast("long").alias("loop_w"))

    @property
    def edges(self) -> DataFrame:
        """All edges (u, v, w) between the nodes, loops included."""
        m = self.members
        pull = m.select(F.col("id").alias("u"), F.col("cls").alias("a"), "k").join(self.arcs, "a").groupBy("u", "b").agg(F.sum(F.col("k") * F.col("w")).alias("pull"))
        other = m.select(F.col("id").alias("v"), F.col("cls").alias("b"), "k")
        apart = pull.join(other, "b").where("u < v").groupBy("u", "v").agg(F.sum(F.col("pull") * F.col("k")).alias("w"))
        return apart.unionAll(self.loops.where("loop_w > 0").select(F.col("id").alias("u"), F.col("id").alias("v"), F.col("loop_w").alias("w")))


@dataclass
class Graph:
    edges: DataFrame
    nodes: DataFrame
    twins: Twins | None = None
    parts: object = None  # a PartGraph of its arcs, where they are cut already

    @staticmethod
    def of(pairs: DataFrame, nodes: DataFrame | None = None) -> Graph:
        """From rows (u, v, w) in any order of ends: parallel edges are added up."""
        edges = pairs.select(F.least("u", "v").cast("long").alias("u"), F.greatest("u", "v").cast("long").alias("v"), F.col("w").cast("long").alias("w")).groupBy("u", "v").agg(F.sum("w").alias("w"))
        ends = edges.select(F.explode(F.array("u", "v")).alias("id")).distinct()
        return Graph(edges, ends if nodes is None else ends.union(nodes.select(F.col("id").cast("long"))).distinct())

    @property
    def spark(self):
        return self.edges.sparkSession

    @cached_property
    def arcs(self) -> DataFrame:
        """(src, dst, w) in both directions, without loops: one pass over the edges."""
        both = F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst"), "w"), F.struct(F.col("v").alias("src"), F.col("u").alias("dst"), "w"))
        return self.edges.where("u <> v").select(F.inline(both))

    @cached_property
    def node_stats(self) -> DataFrame:
        """(id, loop_w, vol): a loop counts twice in its node's volume."""
        ends = F.array(F.struct(F.col("u").alias("id"), F.when(F.col("u") == F.col("v"), F.col("w")).otherwise(0).alias("l"), "w"), F.struct(F.col("v").alias("id"), F.lit(0).cast("long").alias("l"), "w"))
        sums = self.edges.select(F.inline(ends)).groupBy("id").agg(F.sum("l").alias("loop_w"), F.sum("w").alias("vol"))
        zero = F.lit(0).cast("long")
        return self.nodes.join(sums, "id", "left").select("id", F.coalesce("loop_w", zero).alias("loop_w"), F.coalesce("vol", zero).alias("vol"))

    @property
    def held_twins(self) -> Twins | None:
        """The graph by classes of equal nodes, where it is known so and they are few."""
        return self.twins.held if self.twins is not None else None

    def written(self, scratch: Scratch) -> Graph:
        """The same graph in tables of its own; one held by its classes keeps its edges as a plan."""
        if self.held_twins is not None:
            return Graph(self.edges, scratch.write(self.nodes), self.held_twins)
        return Graph(scratch.write(self.edges.select("u", "v", "w")), scratch.write(self.nodes))

    def total_weight(self) -> int:
        if self.held_twins is not None:
            return self.held_twins.weight
        return self.edges.agg(F.sum("w")).first()[0] or 0

    def validate(self) -> None:
        """Raises if ids are null, ends are out of order or unknown, weights not positive, or edges repeated."""
        bad = self.edges.agg(
            F.count_if(F.col("u").isNull() | F.col("v").isNull() | F.col("w").isNull()).alias("null values"), F.count_if(F.expr("u > v")).alias("ends out of order"),
            F.count_if(F.expr("w <= 0")).alias("weights not positive"),
        ).first().asDict()
        bad["repeated edges"] = self.edges.groupBy("u", "v").count().where("count > 1").count()
        bad["repeated or null nodes"] = self.nodes.groupBy("id").count().where("count > 1 OR id IS NULL").count()
        ends = self.edges.select(F.explode(F.array("u", "v")).alias("id"))
        bad["unknown ends"] = ends.join(self.nodes, "id", "left_anti").count()
        found = {k: v for k, v in bad.items() if v}
        if found:
            raise ValueError(f"not a graph: {found}")


def singletons(g: Graph) -> DataFrame:
    return g.nodes.select("id", F.col("id").alias("comm"))


def canonical(assignment: DataFrame) -> DataFrame:
    """The same partition, each community named by its smallest member."""
    names = assignment.groupBy("comm").agg(F.min("id").alias("name"))
    return assignment.join(names, "comm").select("id", F.col("name").alias("comm"))


def check_assignment(g: Graph, assignment: DataFrame) -> None:
    """Raises unless every node has exactly one community."""
    lost = g.nodes.join(assignment, "id", "left_anti").count()
    twice = assignment.groupBy("id").count().where("count > 1").count()
    if lost or twice:
        raise ValueError(f"not a partition: {lost} nodes without community, {twice} with several")


def contract(g: Graph, assignment: DataFrame) -> tuple[Graph, DataFrame]:
    """Communities become nodes, parallel edges are added up, inner edges become loops. Weight and volume stay."""
    twins = g.held_twins
    if twins is not None:
        mapping = assignment.select("id", F.col("comm").alias("super"))
        nodes = mapping.select(F.col("super").alias("id")).distinct()
        small = replace(twins, members=twins.grouped(assignment))
        return Graph(small.edges, nodes, replace(small, nodes=0)), mapping
    comm = g.parts.labels(assignment) if g.parts is not None else None
    if comm is not None:
        mapping = assignment.select("id", F.col("comm").alias("super"))
        return Graph(g.parts.contracted(comm).groupBy("u", "v").agg(F.sum("w").alias("w")), mapping.select(F.col("super").alias("id")).distinct()), mapping
    a, b = assignment.select(F.col("id").alias("u"), F.col("comm").alias("cu")), assignment.select(F.col("id").alias("v"), F.col("comm").alias("cv"))
    ends = g.edges.join(a, "u").join(b, "v").select(F.least("cu", "cv").alias("u"), F.greatest("cu", "cv").alias("v"), "w")
    mapping = assignment.select("id", F.col("comm").alias("super"))
    return Graph(ends.groupBy("u", "v").agg(F.sum("w").alias("w")), mapping.select(F.col("super").alias("id")).distinct()), mapping


def lift(mapping: DataFrame, coarse: DataFrame) -> DataFrame:
    """Each fine node takes the community of the node it was contracted into."""
    return mapping.join(coarse.select(F.col("id").alias("super"), "comm"), "super").select("id", "comm")


def community_graph(g: Graph, assignment: DataFrame) -> tuple[Graph, DataFrame]:
    """The contracted graph and (id, size) of its nodes."""
    small, mapping = contract(g, assignment)
    return small, mapping.groupBy(F.col("super").alias("id")).agg(F.count("*").alias("size"))


def index_nodes(values: DataFrame, column: str) -> DataFrame:
    """(value, id) with dense ids in the order of the distinct values: counts of range partitions, then offsets."""
    ranged = values.select(F.col(column).alias("value")).where(F.col(column).isNotNull()).distinct().repartitionByRange("value").sortWithinPartitions("value")
    placed = ranged.select("value", F.spark_partition_id().alias("p"), (F.monotonically_increasing_id() - F.shiftleft(F.spark_partition_id().cast("long"), 33)).alias("k"))
    sizes = placed.groupBy("p").agg(F.count("*").alias("n"))  # one row a partition
    before = F.sum("n").over(Window.orderBy("p").rowsBetween(Window.unboundedPreceding, -1))
    offsets = sizes.select("p", F.coalesce(before, F.lit(0)).alias("offset"))
    return placed.join(F.broadcast(offsets), "p").select("value", (F.col("offset") + F.col("k")).alias("id"))
