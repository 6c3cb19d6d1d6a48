"""Graphs from tables: co-occurrence, bipartite, hierarchies, texts, pages, time.

Pairs inside a group grow with the square of its size. Builders that pair a group's members take
`max_group`: groups above it are an error rather than silently cut, or are left out where that is the
definition of the graph (frequent shingles say nothing about copies).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shoal.core.graph import Graph, Twins
from shoal.core.storage import Scratch
from shoal.functions.scalar import host, hrefs, prop, shingles
from shoal.sources.tables import load_table

#: Tags in the high bits that keep kinds of nodes apart; keys below them may be as large as 2^56.
NATION, SUPPLIER, REGION, ITEM = 1 << 56, 2 << 56, 3 << 56, 1 << 56
#: Members of a group up to which all pairs are formed by default; larger groups are an error, not a cut.
MAX_GROUP = 50_000
#: Vectors of a block that are compared with a block at once.
KNN_BLOCK = 2_048
#: Turns of one conversation that have numbers of their own.
TURNS = 1 << 24


def keyed(value: Column, most: int = 1 << 56) -> Column:
    """The value, or an error where it would run into the next kind's numbers."""
    return F.when(value.isNull() | ((value >= 0) & (value < most)), value).otherwise(F.raise_error(F.concat(F.lit("a key does not fit its kind of nodes: "), value.cast("string"))).cast("long"))


def cooccurrence(rows: DataFrame, group: str, item: str, max_group: int = MAX_GROUP) -> Graph:
    """Items that share a group; w counts the groups. A group of more than max_group items raises: its pairs are the
    square of its size (link its members to one of them instead, as `all_shared_shingles` does)."""
    pairs = rows.select(F.col(group).alias("k"), F.col(item).cast("long").alias("i")).where("k IS NOT NULL AND i IS NOT NULL").distinct()
    size = F.count("*").over(Window.partitionBy("k"))  # dealt out by k, as the join needs it
    left = pairs.withColumn("n", size).where(F.when(F.col("n") <= max_group, F.lit(True)).otherwise(F.raise_error(F.lit(f"a group of more than {max_group} members: its pairs would explode")).cast("boolean")))
    edges = left.select("k", F.col("i").alias("u")).join(pairs.select("k", F.col("i").alias("v")), "k").where("u < v").groupBy("u", "v").agg(F.count("*").alias("w"))
    return Graph(edges, pairs.select(F.col("i").alias("id")).distinct())


def cooccurrence_twins(rows: DataFrame, group: str, item: str) -> Twins:
    """The graph of `cooccurrence` by its items of equal sets of groups, without their pairs."""
    pairs = rows.select(F.col(group).alias("k"), F.col(item).cast("long").alias("i")).where("k IS NOT NULL AND i IS NOT NULL")
    sets = pairs.groupBy("i").agg(F.array_sort(F.collect_set("k")).alias("s"))
    members = sets.join(sets.groupBy("s").agg(F.min("i").alias("cls")), "s")

    def between(written: DataFrame) -> DataFrame:
        held = written.select("cls", F.explode("s").alias("g"))
        return held.select("g", F.col("cls").alias("a")).join(held.select("g", F.col("cls").alias("b")), "g").where("a <= b").groupBy("a", "b").agg(F.count("*").alias("w"))

    return Twins(members.select(F.col("i").alias("id"), "cls", F.lit(1).cast("long").alias("k"), F.when(F.col("i") == F.col("cls"), F.col("s")).alias("s")), between)


def bipartite(rows: DataFrame, left: Column, right: Column, distinct: bool = False) -> Graph:
    """Edges between two kinds of nodes (ids already apart); w counts the rows, or is 1."""
    pairs = rows.select(left.cast("long").alias("u"), right.cast("long").alias("v"))
    return Graph.of((pairs.distinct() if distinct else pairs).withColumn("w", F.lit(1)))


def basket(spark: SparkSession, d: str) -> Graph:
    return cooccurrence(load_table(spark, d, "lineitem").select("l_orderkey", "l_partkey"), "l_orderkey", "l_partkey")


def cosupply(spark: SparkSession, d: str) -> Graph:
    return cooccurrence(load_table(spark, d, "lineitem").select("l_orderkey", "l_suppkey"), "l_orderkey", "l_suppkey")


def trade(spark: SparkSession, d: str) -> Graph:
    rows = load_table(spark, d, "orders").join(load_table(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    return bipartite(rows, keyed(F.col("o_custkey")), keyed(F.col("l_suppkey")) + SUPPLIER)


def supply(spark: SparkSession, d: str) -> Graph:
    return bipartite(load_table(spark, d, "lineitem"), keyed(F.col("l_partkey")), keyed(F.col("l_suppkey")) + SUPPLIER, distinct=True)


def geo(spark: SparkSession, d: str) -> Graph:
    """Customers and suppliers under nations, nations under regions."""
    c = load_table(spark, d, "customer").select(keyed(F.col("c_custkey")).alias("u"), (F.col("c_nationkey") + NATION).alias("v"))
    s = load_table(spark, d, "supplier").select((keyed(F.col("s_suppkey")) + SUPPLIER).alias("u"), (F.col("s_nationkey") + NATION).alias("v"))
    n = load_table(spark, d, "nation").select((F.col("n_nationkey") + NATION).alias("u"), (F.col("n_regionkey") + REGION).alias("v"))
    return Graph.of(c.union(s).union(n).withColumn("w", F.lit(1)))


def geo_truth(spark: SparkSession, d: str) -> DataFrame:
    """Each node's nation; regions are alone."""
    c = load_table(spark, d, "customer").select(F.col("c_custkey").cast("long").alias("id"), (F.col("c_nationkey") + NATION).cast("long").alias("comm"))
    s = load_table(spark, d, "supplier").select((F.col("s_suppkey") + SUPPLIER).alias("id"), (F.col("s_nationkey") + NATION).cast("long").alias("comm"))
    n = load_table(spark, d, "nation").select((F.col("n_nationkey") + NATION).cast("long").alias("id"), (F.col("n_nationkey") + NATION).cast("long").alias("comm"))
    r = load_table(spark, d, "region").select((F.col("r_regionkey") + REGION).cast("long").alias("id"), (F.col("r_regionkey") + REGION).cast("long").alias("comm"))
    return c.union(s).union(n).union(r)


def planted(spark: SparkSession, d: str, mu10: int = 5) -> tuple[Graph, DataFrame]:
    """A graph with a known truth: each lineitem row draws an edge inside its part's block or, with
    probability mu10/10 by an arithmetic hash, to any part. Truth is the block."""
    n = load_table(spark, d, "part").count()
    block = max(5, n // 50)
    size = n // block
    p = 2_147_483_647
    # The multipliers and moduli of the planting rule
    a, h = F.col("l_partkey"), (F.col("l_orderkey") * 7919 + F.col("l_linenumber").cast("long") * 104729 + F.col("l_suppkey") * 31) % 1000003
    mixed = ((h * 48271 + 11) % p) % 10 < mu10
    any_part = ((h * 69621 + a * 7 + 13) % p) % n
    inside = a % block + block * (((h * 16807 + a * 3 + 5) % p) % size)
    rows = load_table(spark, d, "lineitem").select(a.alias("a"), F.when(mixed, any_part).otherwise(inside).alias("b")).where("a <> b")
    parts = load_table(spark, d, "part").select(F.col("p_partkey").alias("id"))
    return Graph.of(rows.select(F.col("a").alias("u"), F.col("b").alias("v"), F.lit(1).alias("w"))), parts.select("id", (F.col("id") % block).alias("comm"))


def shared_shingles(docs: DataFrame, n: int = 5, most_words: int | None = None, max_df: int = 50) -> Graph:
    """Documents that share word shingles held by at most max_df documents; w counts them."""
    held = docs.select(F.col("doc_id").alias("i"), F.explode(shingles(F.col("text"), n, most_words)).alias("s"))
    rare = held.groupBy("s").agg(F.count("*").alias("df")).where(f"df BETWEEN 2 AND {max_df}").select("s")
    kept = held.join(rare, "s")
    edges = kept.select("s", F.col("i").alias("u")).join(kept.select("s", F.col("i").alias("v")), "s").where("u < v").groupBy("u", "v").agg(F.count("*").alias("w"))
    return Graph.of(edges)


def neardup(spark: SparkSession, d: str) -> Graph:
    return shared_shingles(load_table(spark, d, "documents"))


def all_shared_shingles(docs: DataFrame, n: int = 5, pairs_to: int = 50) -> Graph:
    """All documents; those that share a word shingle are linked, w counts the shingles. A shingle of up to pairs_to
    holders links each pair of them, a more frequent one links each holder to the smallest: no group falls apart,
    and edges grow with the holders."""
    held = docs.where("doc_id IS NOT NULL").select(F.col("doc_id").alias("i"), F.explode(shingles(F.col("text"), n, None)).alias("s")).select("i", F.unhex("s").alias("s")).repartition("s").distinct()
    group, scratch = Window.partitionBy("s"), Scratch(docs.sparkSession, "shingles")
    # each text is cut into shingles once; only the shared ones are written
    kept = scratch.write(held.select("s", "i", F.count("*").over(group).alias("df"), F.min("i").over(group).alias("least")).where("df > 1"))
    some = kept.where(F.col("df") <= pairs_to)
    pairs = some.select("s", F.col("i").alias("u")).join(some.select("s", F.col("i").alias("v")), "s").where("u < v").select("u", "v")
    stars = kept.where((F.col("df") > pairs_to) & (F.col("least") < F.col("i"))).select(F.col("least").alias("u"), F.col("i").alias("v"))
    edges = scratch.write(pairs.union(stars).groupBy("u", "v").agg(F.count("*").alias("w")))
    scratch.drop(kept)
    return Graph.of(edges, docs.where("doc_id IS NOT NULL").select(F.col("doc_id").alias("id")))


def neardup_all(spark: SparkSession, d: str) -> Graph:
    return all_shared_shingles(load_table(spark, d, "documents"))


def _links(spark: SparkSession, d: str) -> DataFrame:
    """(page_id, href) distinct."""
    return load_table(spark, d, "pages").select("page_id", F.explode(hrefs(F.col("html"))).alias("href")).distinct()


def _href_ids(links: DataFrame) -> DataFrame:
    """A number for each distinct href, in their order: counts of ranges first, so no global sort in one task."""
    from shoal.core.graph import index_nodes

    return index_nodes(links, "href").select(F.col("value").alias("href"), (F.col("id") + ITEM).alias("hid"))


def pagelinks(spark: SparkSession, d: str) -> Graph:
    links = _links(spark, d)
    return bipartite(links.join(_href_ids(links), "href"), F.col("page_id"), F.col("hid"))


def pagepages(spark: SparkSession, d: str) -> Graph:
    g = cooccurrence(_links(spark, d), "href", "page_id")
    return Graph(g.edges, g.nodes, cooccurrence_twins(load_table(spark, d, "pages").select("page_id", F.explode(hrefs(F.col("html"))).alias("href")), "href", "page_id"))


def hosts(spark: SparkSession, d: str) -> DataFrame:
    """(host, href, w): links from hosts to hrefs."""
    pages = load_table(spark, d, "pages").select(host(F.col("url")).alias("host"), F.explode(hrefs(F.col("html"))).alias("href"))
    return pages.groupBy("host", "href").agg(F.count("*").alias("w"))


def hosts_graph(spark: SparkSession, d: str) -> Graph:
    from shoal.core.graph import index_nodes

    rows = hosts(spark, d)
    names = index_nodes(rows.select(F.explode(F.array("host", "href")).alias("name")), "name")
    a, b = names.select(F.col("value").alias("host"), F.col("id").alias("u")), names.select(F.col("value").alias("href"), F.col("id").alias("v"))
    return Graph.of(rows.join(a, "host").join(b, "href").select("u", "v", "w"))


def nav_truth(spark: SparkSession, d: str) -> DataFrame:
    """Pages by their set of hrefs."""
    sets = _links(spark, d).groupBy("page_id").agg(F.array_sort(F.collect_set("href")).alias("s"))
    return sets.join(sets.groupBy("s").agg(F.min("page_id").alias("comm")), "s").select(F.col("page_id").alias("id"), "comm")


def turns(spark: SparkSession, d: str) -> Graph:
    """Consecutive turns of a conversation: node conv_id * TURNS + turn."""
    t = load_table(spark, d, "conversations").select(keyed(F.col("conv_id"), 1 << 38).alias("conv_id"), keyed(F.col("turn"), TURNS).alias("turn"))
    node = F.col("conv_id") * TURNS + F.col("turn")
    after = t.select("conv_id", (F.col("turn") - 1).alias("turn"))
    edges = t.join(after, ["conv_id", "turn"]).select(node.alias("u"), (node + 1).alias("v"), F.lit(1).alias("w"))
    return Graph.of(edges, t.select(node.alias("id")))


def turns_truth(spark: SparkSession, d: str) -> DataFrame:
    return load_table(spark, d, "conversations").select((F.col("conv_id") * TURNS + F.col("turn")).alias("id"), F.col("conv_id").alias("comm"))


def coactivity(events: DataFrame, width: str = "hour") -> Graph:
    """Users with an event of one type in one span of time; w counts the spans."""
    keyed = events.select(F.concat_ws("|", "event_type", F.date_trunc(width, "ts").cast("string")).alias("k"), "user_id")
    return cooccurrence(keyed, "k", "user_id")


def coactive(spark: SparkSession, d: str) -> Graph:
    return coactivity(load_table(spark, d, "events"))


def useritem(spark: SparkSession, d: str) -> Graph:
    """Users and (event type, k): item number from the type's place in the alphabet and k."""
    kinds = F.array(*map(F.lit, ("click", "error", "purchase", "signup", "view")))
    place = F.array_position(kinds, F.col("event_type"))
    known = F.when(place > 0, place).otherwise(F.raise_error(F.concat(F.lit("unknown event type: "), F.coalesce("event_type", F.lit("null")))).cast("long"))
    item = known * 100 + keyed(prop(F.col("props"), "k").cast("long"), 100) + ITEM
    return bipartite(load_table(spark, d, "events"), keyed(F.col("user_id")), item)


def _nearest_of_all(vectors: DataFrame, k: int) -> DataFrame:
    """(a, b, s): the k most similar vectors b of each vector a in each block of vectors, the nearest of all among them.

    Terms are added one after the other, as `cosine` adds them, so scores and their ties are the same."""
    known = vectors.where("vec_id IS NOT NULL AND embedding IS NOT NULL AND NOT exists(embedding, x -> x IS NULL)")
    count = max(1, -(-known.count() // KNN_BLOCK))
    dealt = known.select(F.pmod(F.xxhash64("vec_id"), F.lit(count)).alias("block"), F.struct(F.col("vec_id").cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("e")).alias("v"))
    blocks = Scratch(vectors.sparkSession, "knn").write(dealt.groupBy("block").agg(F.array_sort(F.collect_list("v")).alias("v")).repartition(count, "block").select("v"))
    pairs = blocks.toDF("p").hint("shuffle_replicate_nl").crossJoin(blocks.toDF("q"))  # no shuffle: a task reads both its blocks

    def unpacked(block: pa.Scalar) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        e = block.values.field("e")
        size = np.diff(e.offsets.to_numpy())
        if len(set(size.tolist())) > 1:
            raise ValueError("vectors of different lengths have no cosine")
        x = e.flatten().to_numpy(zero_copy_only=False).reshape(len(size), -1)
        norm = np.zeros(len(x))
        for column in x.T:
            norm += column * column
        if not norm.all():
            raise ValueError("a vector of length 0 has no cosine")
        return block.values.field("id").to_numpy(zero_copy_only=False), x, np.sqrt(norm)

    def nearest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for p, q in zip(batch.column(0), batch.column(1), strict=True):
                (a, x, nx), (b, y, ny) = unpacked(p), unpacked(q)  # ids rise
                if x.shape[1] != y.shape[1]:
                    raise ValueError("vectors of different lengths have no cosine")
                yt = np.ascontiguousarray(y.T)
                for low in range(0, len(a), 64):
                    part = slice(low, low + 64)
                    s = np.zeros((len(a[part]), len(b)))
                    for d in range(len(yt)):
                        s += x[part, d, None] * yt[d]
                    s /= nx[part, None] * ny
                    order = np.where(a[part, None] == b, np.inf, np.where(np.isnan(s), -np.inf, -s))  # least first; itself never
                    bound = np.partition(order, k - 1, axis=1)[:, k - 1, None] if k < len(b) else np.inf
                    i, j = np.nonzero((order <= bound) & (a[part, None] != b))
                    by = np.lexsort((j, order[i, j], i))
                    i, j = i[by], j[by]
                    first = np.arange(len(i)) - np.searchsorted(i, i) < k
                    i, j = i[first], j[first]
                    yield pa.RecordBatch.from_arrays([pa.array(a[part][i]), pa.array(b[j]), pa.array(s[i, j])], ["a", "b", "s"])

    return pairs.mapInArrow(nearest, "a long, b long, s double")


def knn_graph(vectors: DataFrame, k: int = 10, bands: int = 0, seed: int = 0) -> Graph:
    """Cosine neighbours. bands=0 compares all pairs, blocks of vectors with blocks as arrays; with bands, only
    pairs whose signs agree on all hyperplanes of a band are compared: approximate, for large tables. A vector that
    is null or holds a null has no neighbours."""
    from shoal.functions.scalar import cosine

    left = vectors.select(F.col("vec_id").alias("a"), F.col("embedding").alias("x"))
    right = vectors.select(F.col("vec_id").alias("b"), F.col("embedding").alias("y"))
    if bands == 0:
        nearest = _nearest_of_all(vectors, k)
        scored = nearest.select("a", F.struct("s", (-F.col("b")).alias("nb")).alias("c"))
    else:
        planes = 8

        def key(c: str, band: int) -> Column:
            bits = []
            for p in range(planes):
                sign = F.aggregate(F.transform(F.col(c), lambda x, i, p=p: x.cast("double") * (F.pmod(F.xxhash64(i, F.lit((band * planes + p) * 7919 + seed)), F.lit(2001)) - 1000)), F.lit(0.0), lambda s, x: s + x)
                bits.append((sign > 0).cast("string"))
            return F.concat_ws("", F.lit(str(band)), *bits)

        lk = left.select("a", "x", F.explode(F.array(*(key("x", i) for i in range(bands)))).alias("k"))
        rk = right.select("b", "y", F.explode(F.array(*(key("y", i) for i in range(bands)))).alias("k"))
        pairs = lk.join(rk, "k").where("a <> b").dropDuplicates(["a", "b"])
        scored = pairs.select("a", F.struct(cosine(F.col("x"), F.col("y")).alias("s"), (-F.col("b")).alias("nb")).alias("c"))
    top = scored.groupBy("a").agg(F.slice(F.sort_array(F.collect_list("c"), asc=False), 1, k).alias("t"))
    edges = top.select("a", F.explode("t").alias("t")).select(F.least("a", -F.col("t.nb")).alias("u"), F.greatest("a", -F.col("t.nb")).alias("v")).distinct().withColumn("w", F.lit(1))
    return Graph.of(edges, vectors.select(F.col("vec_id").alias("id")))


# -- clean-up --------------------------------------------------------------------------------------------


def without_loops(g: Graph) -> Graph:
    return Graph(g.edges.where("u <> v"), g.nodes)


def filter_weight(g: Graph, least: int) -> Graph:
    return Graph(g.edges.where(F.col("w") >= least), g.nodes)


def induced(g: Graph, nodes: DataFrame) -> Graph:
    keep = nodes.select("id")
    edges = g.edges.join(keep.withColumnRenamed("id", "u"), "u", "left_semi").join(keep.withColumnRenamed("id", "v"), "v", "left_semi")
    return Graph(edges.select("u", "v", "w"), g.nodes.join(keep, "id", "left_semi"))


def largest_component(g: Graph) -> Graph:
    from shoal.measures.profile import connected_components

    c = connected_components(g)
    top = c.groupBy("comm").count().orderBy(F.desc("count"), "comm").limit(1).select("comm")
    return induced(g, c.join(F.broadcast(top), "comm", "left_semi"))


def k_core(g: Graph, k: int, max_rounds: int = 100) -> Graph:
    """What is left after taking away nodes of degree below k again and again."""
    from shoal.core.storage import Scratch
    from shoal.measures.profile import degrees

    scratch, now = Scratch(g.spark, "core"), without_loops(g)
    for _ in range(max_rounds):
        keep = degrees(now).where(F.col("degree") >= k)
        small = induced(now, keep)
        small = Graph(scratch.write(small.edges), scratch.write(small.nodes))
        if small.nodes.count() == now.nodes.count():
            return small
        now = small
    raise RuntimeError("core not settled")
