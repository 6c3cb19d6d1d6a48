"""The registered queries of the community-detection library, with SQL that yields the same rows where SQL can."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shoal import oracle_text as sql
from shoal.core.graph import Graph, canonical, community_graph, contract, lift, singletons
from shoal.core.storage import Scratch
from shoal.functions import surface
from shoal.graphs import builders
from shoal.measures import agreement, profile, quality
from shoal.measures import scores as score_table
from shoal.operators import baselines, ensemble, moves, multilevel, propagation, relational, sampling
from shoal.sources import generators
from shoal.sources.tables import load_table
from shoal.streaming import edges as streaming

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def register(name: str, run: Query, oracle: str | None = None) -> None:
    QUERIES[name] = run
    if oracle:
        ORACLES[name] = oracle


def _planted(spark: SparkSession, d: str) -> tuple[Graph, DataFrame]:
    g, t = builders.planted(spark, d)
    return g, t.join(g.nodes, "id", "left_semi")


def _geo(spark: SparkSession, d: str) -> tuple[Graph, DataFrame]:
    return builders.geo(spark, d), builders.geo_truth(spark, d)


def _turns(spark: SparkSession, d: str) -> tuple[Graph, DataFrame]:
    return builders.turns(spark, d), builders.turns_truth(spark, d)


def _pages(spark: SparkSession, d: str) -> tuple[Graph, DataFrame]:
    return builders.pagepages(spark, d), builders.nav_truth(spark, d)


WITH_TRUTH = {"planted": _planted, "geo": _geo, "turns": _turns, "pagepages": _pages}
GRAPHS: dict[str, Callable[[SparkSession, str], Graph]] = {
    "basket": builders.basket, "trade": builders.trade, "supply": builders.supply, "cosupply": builders.cosupply, "geo": builders.geo, "planted": lambda s, d: builders.planted(s, d)[0],
    "neardup": builders.neardup, "pagelinks": builders.pagelinks, "pagepages": builders.pagepages, "turns": builders.turns, "coactive": builders.coactive, "useritem": builders.useritem,
}


# -- graphs and their profiles -----------------------------------------------------------------------------

for _name, _build in GRAPHS.items():
    register(f"graph_{_name}", lambda s, d, b=_build: b(s, d).edges, sql.query(_name, select="SELECT u, v, w FROM e"))
register("graph_hosts", builders.hosts, r"""WITH l AS (SELECT regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) host, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) href FROM pages) SELECT host, href, count(*) w FROM l GROUP BY 1, 2""")
register("profile_degree", lambda s, d: profile.degree_profile(builders.geo(s, d)), sql.query("geo", sql.ARCS, select="SELECT degree, count(*) nodes FROM (SELECT id, count(src) degree FROM n LEFT JOIN arcs ON src = id GROUP BY id) GROUP BY 1"))
register("profile_maxdeg", lambda s, d: profile.degrees(builders.basket(s, d)).agg(F.count("*").alias("n"), F.max("degree").alias("max_degree")), sql.query("basket", sql.ARCS, select="SELECT count(*) n, max(degree) max_degree FROM (SELECT id, count(src) degree FROM n LEFT JOIN arcs ON src = id GROUP BY id)"))
register("components_geo", lambda s, d: profile.connected_components(builders.geo(s, d)), sql.query("geo", select="""SELECT id, CASE WHEN id >= 216172782113783808 THEN coalesce(r.m, id) ELSE m.m END comm
FROM (SELECT id, r_of FROM (SELECT c_custkey id, n_regionkey r_of FROM customer JOIN nation ON n_nationkey = c_nationkey UNION ALL SELECT s_suppkey + 144115188075855872, n_regionkey FROM supplier JOIN nation ON n_nationkey = s_nationkey
  UNION ALL SELECT n_nationkey::BIGINT + 72057594037927936, n_regionkey FROM nation UNION ALL SELECT r_regionkey::BIGINT + 216172782113783808, r_regionkey FROM region)) x
LEFT JOIN (SELECT n_regionkey k, min(c_custkey) m FROM customer JOIN nation ON n_nationkey = c_nationkey GROUP BY 1) m ON m.k = r_of
LEFT JOIN (SELECT n_regionkey k, min(c_custkey) m FROM customer JOIN nation ON n_nationkey = c_nationkey GROUP BY 1) r ON r.k = r_of"""))
register("triangles", lambda s, d: profile.triangles(builders.pagepages(s, d)), sql.query("pagepages", sql.ARCS, select="""SELECT id, count(*) triangles FROM (SELECT unnest([x.u, x.v, y.v]) id FROM e x JOIN e y ON y.u = x.v JOIN e z ON z.u = x.u AND z.v = y.v) GROUP BY 1"""))
register("local_clustering", lambda s, d: profile.local_clustering(builders.pagepages(s, d)), sql.query("pagepages", sql.ARCS, """dg AS (SELECT id, count(src) degree FROM n LEFT JOIN arcs ON src = id GROUP BY id),
tr AS (SELECT id, count(*) t FROM (SELECT unnest([x.u, x.v, y.v]) id FROM e x JOIN e y ON y.u = x.v JOIN e z ON z.u = x.u AND z.v = y.v) GROUP BY 1)""", select="SELECT id, degree, coalesce(t, 0) triangles, round(CASE WHEN degree < 2 THEN 0 ELSE coalesce(t, 0) / (degree * (degree - 1) / 2) END, 6) clustering FROM dg LEFT JOIN tr USING (id)"))
# -- measures -----------------------------------------------------------------------------------------------

for _name, _both in WITH_TRUTH.items():
    _tail = "" if _name == "planted" else f"_{_name}"
    register(f"coverage{_tail}", lambda s, d, b=_both: quality.coverage(*b(s, d)), sql.query(_name, select="SELECT sum(CASE WHEN a.comm = b.comm THEN w ELSE 0 END)::BIGINT inner_w, sum(w)::BIGINT total_w, round(sum(CASE WHEN a.comm = b.comm THEN w ELSE 0 END) / sum(w), 6) coverage FROM e JOIN t a ON a.id = u JOIN t b ON b.id = v"))
    for _g, _gn in ((1, ""), (2, "_gamma")):
        register(f"modularity{_gn}{_tail}", lambda s, d, b=_both, g=_g: quality.modularity(*b(s, d), gamma=g), sql.query(_name, sql.VOL, f"""i AS (SELECT a.comm, sum(w) w FROM e JOIN t a ON a.id = u JOIN t b ON b.id = v WHERE a.comm = b.comm GROUP BY 1),
c AS (SELECT comm, sum(vol) v FROM vol JOIN t USING (id) GROUP BY 1)""", select=f"SELECT count(*) communities, round(sum(coalesce(w, 0)) / any_value(tw) - {_g} * sum(v * v)::DOUBLE / (4.0::DOUBLE * any_value(tw) * any_value(tw)), 6) modularity FROM c LEFT JOIN i USING (comm), tot"))


def _terms(s: SparkSession, d: str) -> DataFrame:
    g, t = _planted(s, d)
    return quality.modularity_terms(g, t, g.total_weight())


register("modularity_terms", _terms, sql.query("planted", sql.VOL, """i AS (SELECT a.comm, sum(w)::BIGINT w FROM e JOIN t a ON a.id = u JOIN t b ON b.id = v WHERE a.comm = b.comm GROUP BY 1),
c AS (SELECT comm, sum(vol)::BIGINT v, count(*) size FROM vol JOIN t USING (id) GROUP BY 1)""", select="SELECT comm, size, v vol, coalesce(w, 0) inner_w, round(coalesce(w, 0)::DOUBLE / tw - (v::DOUBLE / (2.0::DOUBLE * tw)) * (v::DOUBLE / (2.0::DOUBLE * tw)), 9) term FROM c LEFT JOIN i USING (comm), tot"))
register("node_volume", lambda s, d: builders.planted(s, d)[0].node_stats.select("id", "vol"), sql.query("planted", sql.VOL, select="SELECT id, vol FROM vol"))
register("community_volume", lambda s, d: moves.community_volume(*_planted(s, d)), sql.query("planted", sql.VOL, select="SELECT comm, sum(vol)::BIGINT vol, count(*) size FROM vol JOIN t USING (id) GROUP BY 1"))
register("weight_to_comm", lambda s, d: moves.weight_to_communities(*_planted(s, d)), sql.query("planted", sql.ARCS, select="SELECT src id, comm, sum(w)::BIGINT w FROM arcs JOIN t ON id = dst GROUP BY 1, 2"))
register("singletons", lambda s, d: singletons(builders.geo(s, d)), sql.query("geo", select="SELECT id, id comm FROM n"))
register("community_sizes", lambda s, d: quality.community_sizes(_geo(s, d)[1]), sql.query("geo", select="SELECT comm, count(*) size FROM t GROUP BY 1"))
register("size_histogram", lambda s, d: quality.size_histogram(_geo(s, d)[1]), sql.query("geo", select="SELECT size, count(*) communities FROM (SELECT comm, count(*) size FROM t GROUP BY 1) GROUP BY 1"))


def _lp_after(s: SparkSession, d: str, name: str, rounds: int = 1, slots: int = 1, **k) -> tuple[Graph, DataFrame]:
    """The state after so many rounds of the library's loop, which may not stop earlier by its own rule."""
    g, scratch = GRAPHS[name](s, d), Scratch(s, "rounds")
    g = Graph(scratch.write(g.edges), scratch.write(g.nodes))
    return g, propagation.propagate_labels(g, theta=-1, max_rounds=rounds, schedule="sync" if slots == 1 else "semi", slots=slots, rename=False, **k)


_LP2 = [sql.ARCS, sql.ONE, sql.lp_round("s0", "s1"), sql.lp_round("s1", "s2")]


def _two_partitions(s: SparkSession, d: str) -> tuple[Graph, DataFrame, DataFrame]:
    g, state = _lp_after(s, d, "planted", 2)
    return g, _planted(s, d)[1], state


register("edge_rand", lambda s, d: agreement.edge_rand(*_two_partitions(s, d)), sql.query("planted", *_LP2, select="SELECT count(*) FILTER ((a.comm = b.comm) = (x.comm = y.comm)) agree, count(*) edges, round(count(*) FILTER ((a.comm = b.comm) = (x.comm = y.comm)) / count(*), 6) edge_rand FROM e JOIN t a ON a.id = u JOIN t b ON b.id = v JOIN s2 x ON x.id = u JOIN s2 y ON y.id = v WHERE u <> v"))
_PAIR = sql.query("planted", *_LP2, """k AS (SELECT a.comm x, b.comm y, count(*)::DOUBLE n FROM t a JOIN s2 b USING (id) GROUP BY 1, 2), j AS (SELECT sum(n * (n - 1) / 2) nij, sum(n) n, sum(n * ln(n)) hj FROM k),
r AS (SELECT sum(a * (a - 1) / 2) ai, sum(a * ln(a)) hx FROM (SELECT sum(n) a FROM k GROUP BY x)), c AS (SELECT sum(b * (b - 1) / 2) bj, sum(b * ln(b)) hy FROM (SELECT sum(n) b FROM k GROUP BY y)),
m AS (SELECT *, n * (n - 1) / 2 p FROM j, r, c)""", select="SELECT {} FROM m")
_PAIRED = {"pair_rand": "round((p + 2 * nij - ai - bj) / p, 6) pair_rand", "adjusted_rand": "round((nij - ai * bj / p) / ((ai + bj) / 2 - ai * bj / p), 6) adjusted_rand", "nmi": "round(2 * (ln(n) + (hj - hx - hy) / n) / (ln(n) - hx / n + ln(n) - hy / n), 6) nmi"}
for _name, _select in _PAIRED.items():
    register(_name, lambda s, d, n=_name: agreement.pair_rand(*_two_partitions(s, d)[1:]).select(n), _PAIR.format(_select))

# -- label propagation --------------------------------------------------------------------------------------

_PLANS = {"": {}, "_task": {"state": "task"}, "_broadcast": {"state": "broadcast"}, "_shuffle": {"state": "shuffle"}, "_no_frontier": {"state": "broadcast", "frontier": False}}


def _register_rounds(name: str, graph: str, rounds: int, slots: int, oracle: str, plans: tuple[str, ...], **k) -> None:
    """One query a physical plan of the loop, all with the same SQL."""
    for plan in plans:
        register(f"{name}{plan}", lambda s, d, p=plan: _lp_after(s, d, graph, rounds, slots, **k, **_PLANS[p])[1], oracle)


_register_rounds("lp_dominant_step", "planted", 1, 1, sql.query("planted", sql.ARCS, sql.ONE, sql.lp_round("s0", "s1"), select="SELECT id, comm FROM s1"), ("", "_shuffle"))
_register_rounds("lp_sync_r3", "basket", 3, 1, sql.query("basket", sql.ARCS, sql.ONE, *(sql.lp_round(f"s{i}", f"s{i + 1}") for i in range(3)), select="SELECT id, comm FROM s3"), ("", "_broadcast", "_shuffle"))
_register_rounds("lp_ties_min", "geo", 2, 1, sql.query("geo", sql.ARCS, sql.ONE, *(sql.lp_round(f"s{i}", f"s{i + 1}", "min") for i in range(2)), select="SELECT id, comm FROM s2"), ("", "_broadcast"), ties="min")
_register_rounds("lp_ties_hash", "geo", 2, 1, sql.query("geo", sql.ARCS, sql.ONE, *(sql.lp_round(f"s{i}", f"s{i + 1}", "hash") for i in range(2)), select="SELECT id, comm FROM s2"), ("", "_shuffle"), ties="hash")
_register_rounds("lp_unweighted_round", "trade", 2, 1, sql.query("trade", sql.ARCS, sql.ONE, *(sql.lp_round(f"s{i}", f"s{i + 1}", weighted=False) for i in range(2)), select="SELECT id, comm FROM s2"), ("", "_broadcast"), weighted=False)


def _slotted(rounds: int, slots: int) -> list[str]:
    out = [sql.ARCS, sql.ONE]
    k = 0
    for r in range(1, rounds + 1):
        for i in range(slots):
            out.append(sql.lp_round(f"s{k}", f"s{k + 1}", where=f"{sql.slot('o.id', r, slots)} = {i}"))
            k += 1
    return out


_register_rounds("lp_semi_k2", "planted", 2, 2, sql.query("planted", *_slotted(2, 2), select="SELECT id, comm FROM s4"), ("", "_broadcast", "_shuffle", "_no_frontier"))
_register_rounds("lp_bipartite_semi", "trade", 2, 2, sql.query("trade", *_slotted(2, 2), select="SELECT id, comm FROM s4"), ("", "_shuffle"))


def _settled_sql(graph: str, rounds: int) -> str:
    """Whole runs: rounds beyond the last change alter nothing, so more of them than needed give the settled state."""
    parts = [p.replace(" AS (", " AS MATERIALIZED (") for p in _slotted(rounds, 2)]
    return sql.query(graph, *parts, sql.named(f"s{2 * rounds}", "r"), select="SELECT id, comm FROM r")


for _name in ("pagepages", "geo", "turns", "pagelinks"):
    # theta=0: by default a run of over 100,000 nodes ends while a few still change
    register(f"lp_settled_{_name}", lambda s, d, b=GRAPHS[_name]: propagation.propagate_labels(b(s, d), theta=0), _settled_sql(_name, 12))


def _round_stats(s: SparkSession, d: str) -> DataFrame:
    g, scratch = builders.planted(s, d)[0], Scratch(s, "rounds")
    g = Graph(scratch.write(g.edges), scratch.write(g.nodes))
    states = [singletons(g), *(propagation.propagate_labels(g, theta=-1, schedule="sync", max_rounds=r, rename=False) for r in (1, 2, 3))]
    rows = None
    for r in range(3):
        one = states[r].join(states[r + 1].select("id", F.col("comm").alias("c")), "id").agg(F.count_if(F.col("comm") != F.col("c")).alias("updated"), F.count_distinct("c").alias("labels")).select(F.lit(r + 1).alias("round"), "updated", "labels")
        rows = one if rows is None else rows.union(one)
    return rows


register("lp_round_stats", _round_stats, sql.query("planted", sql.ARCS, sql.ONE, *(sql.lp_round(f"s{i}", f"s{i + 1}") for i in range(3)), select=" UNION ALL ".join(f"SELECT {i + 1} round, count(*) FILTER (a.comm <> b.comm) updated, count(DISTINCT b.comm) labels FROM s{i} a JOIN s{i + 1} b USING (id)" for i in range(3))))
register("lp_majority_violations", lambda s, d: propagation.majority_violations(*_lp_after(s, d, "planted", 2)), sql.query("planted", *_LP2, "vo AS (SELECT a.src id, l.comm c, sum(a.w)::BIGINT w FROM arcs a JOIN s2 l ON l.id = a.dst GROUP BY 1, 2)", select="SELECT id, comm, coalesce(max(w) FILTER (c = comm), 0) w, max(w) best FROM vo JOIN s2 USING (id) GROUP BY 1, 2 HAVING coalesce(max(w) FILTER (c = comm), 0) < max(w)"))

# -- moves, contraction, levels -------------------------------------------------------------------------------


def _scores(s: SparkSession, d: str, gamma=1, start=None) -> DataFrame:
    g, t = _planted(s, d)
    return moves.move_scores(g, start(g) if start else t, g.total_weight(), gamma)


_MOVE = [sql.ARCS, sql.VOL]
register("move_gain", lambda s, d: _scores(s, d).select("id", "from_comm", "to_comm", F.col("score").cast("long").alias("score")), sql.query("planted", *_MOVE, sql.gains("t"), select="SELECT id, from_comm, to_comm, score::BIGINT score FROM sc"))
register("move_gain_gamma", lambda s, d: _scores(s, d, (3, 2)).select("id", "from_comm", "to_comm", F.col("score").cast("long").alias("score")), sql.query("planted", *_MOVE, sql.gains("t", 3, 2), select="SELECT id, from_comm, to_comm, score::BIGINT score FROM sc"))
register("best_move", lambda s, d: moves.best_moves(_scores(s, d, start=singletons)).withColumn("score", F.col("score").cast("long")), sql.query("planted", *_MOVE, sql.ONE, sql.gains("s0"), "b AS (SELECT *, row_number() OVER (PARTITION BY id ORDER BY score DESC, to_comm) k FROM sc WHERE score > 0 AND NOT (sf AND st AND to_comm > from_comm))", select="SELECT id, from_comm, to_comm, score::BIGINT score FROM b WHERE k = 1"))


#: Rounds that end by their number only, and keep the last state.
_ALL_ROUNDS = {"slots": 2, "guards": {"slots", "singleton"}, "min_gain": float("-inf")}


def _moved(s: SparkSession, d: str, name: str, rounds: int, start: str = "one", **k) -> tuple[Graph, DataFrame]:
    g, t = WITH_TRUTH[name](s, d)
    scratch = Scratch(s, "rounds")
    g = Graph(scratch.write(g.edges), scratch.write(g.nodes))
    return g, moves.local_move(g, None if start == "one" else scratch.write(t), max_rounds=rounds, rename=False, **_ALL_ROUNDS, **k)[0]


def _moved_sql(start: str, rounds: int) -> list[str]:
    out, k = [sql.ARCS, sql.VOL, sql.ONE if start == "one" else "s0 AS (SELECT id, comm FROM t)"], 0
    for r in range(1, rounds + 1):
        for i in range(2):
            out.append(sql.move_round(f"s{k}", f"s{k + 1}", where=f"{sql.slot('id', r, 2)} = {i}"))
            k += 1
    return out


_WAYS = {"": {}, "_broadcast": {"state": "broadcast"}, "_shuffle": {"state": "shuffle"}, "_delta": {"state": "shuffle", "weights": "delta"}}
for _way, _k in _WAYS.items():
    register(f"move_r1{_way}", lambda s, d, k=_k: _moved(s, d, "planted", 1, **k)[1], sql.query("planted", *_moved_sql("one", 1), select="SELECT id, comm FROM s2"))
register("move_r3", lambda s, d: _moved(s, d, "geo", 3)[1], sql.query("geo", *_moved_sql("one", 3), select="SELECT id, comm FROM s6"))
register("move_r3_delta", lambda s, d: _moved(s, d, "geo", 3, state="broadcast", weights="delta")[1], ORACLES["move_r3"])
register("refine_step", lambda s, d: _moved(s, d, "pagepages", 1, "truth")[1], sql.query("pagepages", *_moved_sql("truth", 1), select="SELECT id, comm FROM s2"))
register("refine_step_shuffle", lambda s, d: _moved(s, d, "pagepages", 1, "truth", state="shuffle")[1], ORACLES["refine_step"])
register("contract", lambda s, d: contract(*_planted(s, d))[0].edges, sql.query("planted", sql.contracted("e", "t", "g1"), select="SELECT u, v, w FROM g1"))


def _contract_twice(s: SparkSession, d: str) -> DataFrame:
    small, _ = contract(*_planted(s, d))
    return contract(small, small.nodes.select("id", (F.col("id") % 7).alias("comm")))[0].edges


register("contract_twice", _contract_twice, sql.query("planted", sql.contracted("e", "t", "g1"), "t2 AS (SELECT DISTINCT comm id, comm % 7 comm FROM t)", sql.contracted("g1", "t2", "g2"), select="SELECT u, v, w FROM g2"))


def _lift(s: SparkSession, d: str) -> DataFrame:
    small, mapping = contract(*_planted(s, d))
    return lift(mapping, small.nodes.select("id", (F.col("id") % 7).alias("comm")))


register("lift", _lift, sql.query("planted", select="SELECT id, comm % 7 comm FROM t"))


def _two_levels(s: SparkSession, d: str, **k) -> DataFrame:
    g, scratch = builders.turns(s, d), Scratch(s, "rounds")
    return multilevel.multilevel(Graph(scratch.write(g.edges), scratch.write(g.nodes)), max_levels=2, max_rounds=2, **_ALL_ROUNDS, **k)


def _two_levels_sql() -> str:
    parts = [*_moved_sql("one", 2), sql.named("s4", "m"), sql.contracted("e", "m", "g1"), "arcs1 AS (SELECT u src, v dst, w FROM g1 WHERE u <> v UNION ALL SELECT v, u, w FROM g1 WHERE u <> v)", "vol1 AS (SELECT m.comm id, sum(vol) vol FROM m JOIN vol USING (id) GROUP BY 1)", "c0 AS (SELECT id, id comm FROM vol1)"]
    k = 0
    for r in (1, 2):
        for i in range(2):
            parts.append(sql.move_round(f"c{k}", f"c{k + 1}", vol="vol1", arcs="arcs1", where=f"{sql.slot('id', r, 2)} = {i}"))
            k += 1
    return sql.query("turns", *parts, "f AS (SELECT m.id, c4.comm FROM m JOIN c4 ON c4.id = m.comm)", sql.named("f", "r"), select="SELECT id, comm FROM r")


register("multilevel_2level", _two_levels, _two_levels_sql())
register("multilevel_2level_broadcast", lambda s, d: _two_levels(s, d, state="broadcast"), _two_levels_sql())
register("community_graph", lambda s, d: community_graph(*_pages(s, d))[1], sql.query("pagepages", select="SELECT comm id, count(*) size FROM t GROUP BY 1"))

# -- ensembles ------------------------------------------------------------------------------------------------


def _runs(s: SparkSession, d: str) -> tuple[Graph, DataFrame]:
    g = builders.planted(s, d)[0]
    scratch = Scratch(s, "runs")
    g = Graph(scratch.write(g.edges), scratch.write(g.nodes))
    one = {"theta": -1, "schedule": "sync", "max_rounds": 1, "rename": False}
    a, b = propagation.propagate_labels(g, **one), propagation.propagate_labels(g, ties="min", **one)
    c = propagation.propagate_labels(g, start=a, **one)
    return g, a.select(F.lit(0).alias("run"), "id", "comm").union(b.select(F.lit(1), "id", "comm")).union(c.select(F.lit(2), "id", "comm"))


_RUNS = [sql.ARCS, sql.ONE, sql.lp_round("s0", "a"), sql.lp_round("s0", "b", "min"), sql.lp_round("a", "c")]
_CORE = "co AS (SELECT a.id, min(a.id) OVER (PARTITION BY a.comm, b.comm, c.comm) comm FROM a JOIN b USING (id) JOIN c USING (id))"
register("consensus_exact", lambda s, d: ensemble.consensus_core(_runs(s, d)[1]), sql.query("planted", *_RUNS, _CORE, select="SELECT id, comm FROM co"))
_M = 4294967296
register("consensus_hash", lambda s, d: ensemble.consensus_core(_runs(s, d)[1], "mul33"), sql.query("planted", *_RUNS, f"hh AS (SELECT a.id, (((5381 * 33 + a.comm) % {_M} * 33 + b.comm) % {_M} * 33 + c.comm) % {_M} h FROM a JOIN b USING (id) JOIN c USING (id))", select="SELECT id, min(id) OVER (PARTITION BY h) comm FROM hh"))
register("contested_edges", lambda s, d: quality.contested_edges(*_runs(s, d)), sql.query("planted", *_RUNS, "al AS (SELECT 0 run, * FROM a UNION ALL SELECT 1, * FROM b UNION ALL SELECT 2, * FROM c)", select="SELECT u, v, w, count(*) FILTER (x.comm = y.comm) inside_runs, count(*) runs FROM e JOIN al x ON x.id = u JOIN al y ON y.id = v AND y.run = x.run WHERE u <> v GROUP BY 1, 2, 3 HAVING count(*) FILTER (x.comm = y.comm) BETWEEN 1 AND count(*) - 1"))
register("ensemble_core_contract", lambda s, d: (lambda g, r: contract(g, ensemble.consensus_core(r))[0].edges)(*_runs(s, d)), sql.query("planted", *_RUNS, _CORE, sql.contracted("e", "co", "g1"), select="SELECT u, v, w FROM g1"))

# -- baselines ------------------------------------------------------------------------------------------------


def _pairing(pairing: str, state: str | None = None) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        g, scratch = builders.planted(s, d)[0], Scratch(s, "pairing")
        g = Graph(scratch.write(g.edges), scratch.write(g.nodes))
        return baselines.agglomerate(g, pairing, max_levels=1, state=state) if state else baselines.pairing_step(g, g.total_weight(), pairing, scratch)

    return run


_BEST = """ms AS (SELECT src c, dst d, 2 * tw * w - x.vol * y.vol sc FROM arcs JOIN vol x ON x.id = src JOIN vol y ON y.id = dst, tot),
bp AS (SELECT c, d FROM (SELECT *, row_number() OVER (PARTITION BY c ORDER BY sc DESC, least(c, d), greatest(c, d)) k FROM ms WHERE sc > 0) WHERE k = 1),
mu AS (SELECT p.c, least(p.c, p.d) r FROM bp p JOIN bp q ON q.c = p.d AND q.d = p.c)"""
register("agglomerate_matching_r1", _pairing("matching"), sql.query("planted", *_MOVE, _BEST, select="SELECT id, min(id) OVER (PARTITION BY coalesce(r, id)) comm FROM n LEFT JOIN mu ON c = id"))
register("agglomerate_star_r1", _pairing("star"), sql.query("planted", *_MOVE, _BEST, "st AS (SELECT c, r FROM mu UNION ALL SELECT p.c, m.r FROM bp p JOIN mu m ON m.c = p.d WHERE p.c NOT IN (SELECT c FROM mu))", select="SELECT id, min(id) OVER (PARTITION BY coalesce(r, id)) comm FROM n LEFT JOIN st ON c = id"))

for _kind in ("matching", "star"):
    register(f"agglomerate_{_kind}_level", _pairing(_kind, "auto"), ORACLES[f"agglomerate_{_kind}_r1"])

# -- whole runs (rows only: tests hold their invariants) --------------------------------------------------------

DETECTORS: dict[str, Callable[[Graph], DataFrame]] = {
    "lp": propagation.propagate_labels, "multilevel": lambda g: multilevel.multilevel(g), "refined": lambda g: multilevel.multilevel(g, refine=True), "ensemble": lambda g: ensemble.ensemble(g),
    "agglomerate_star": lambda g: baselines.agglomerate(g, "star"), "agglomerate_matching": lambda g: baselines.agglomerate(g, "matching"), "sequential": lambda g: baselines.sequential_multilevel(g),
    "greedy": lambda g: baselines.randomized_greedy(g), "core_groups": lambda g: baselines.core_group_ensemble(g), "core_groups_iterated": lambda g: baselines.core_group_ensemble(g, iterate=True),
    "greedy_batch": lambda g: baselines.randomized_greedy_batch(g), "lp_original": lambda g: baselines.original_label_propagation(g),
}
for _name, _detect in DETECTORS.items():
    register(f"{_name}_pagepages", lambda s, d, f=_detect: f(builders.pagepages(s, d)))
register("lp_neardup", lambda s, d: propagation.propagate_labels(builders.neardup_all(s, d)))
register("lp_sync_cycle", lambda s, d: propagation.propagate_labels(builders.geo(s, d), schedule="sync", frontier=False, max_rounds=8))
register("multilevel_delta_weights", lambda s, d: moves.local_move(builders.pagepages(s, d), weights="delta", max_rounds=3)[0])
register("multilevel_independent_set", lambda s, d: moves.local_move(builders.pagepages(s, d), schedule="independent", max_rounds=3)[0])


def _gamma_extremes(s: SparkSession, d: str) -> DataFrame:
    g = builders.turns(s, d)
    out = None
    for gamma in ((0, 1), (2 * g.total_weight(), 1)):
        one = multilevel.multilevel(g, gamma=gamma).agg(F.count_distinct("comm").alias("communities"), F.count("*").alias("n")).select(F.lit(gamma[0]).alias("gamma"), "communities", "n")
        out = one if out is None else out.union(one)
    return out


register("gamma_extremes", _gamma_extremes)
register("knn_graph", lambda s, d: builders.knn_graph(load_table(s, d, "embeddings")).edges)


def _orders(s: SparkSession, d: str) -> tuple[DataFrame, int]:
    """Orders, which draw one edge each, and their number."""
    draws = load_table(s, d, "orders").select(F.xxhash64("o_orderkey", "o_custkey").alias("id"))
    return draws, draws.count()


def _customers(s: SparkSession, d: str) -> tuple[DataFrame, int]:
    """Places of the customers with orders, by their keys, and their number (2 at least, as scales are logarithms)."""
    nodes = generators.dense(load_table(s, d, "orders"), "o_custkey")
    return nodes, max(2, nodes.count())


def _two_density(s: SparkSession, d: str) -> Graph:
    (nodes, n), (draws, _) = _customers(s, d), _orders(s, d)
    return generators.two_density(s, n, 20, 0.3, 0.002, nodes=nodes, draws=draws)[0]


def _heavy_tail(s: SparkSession, d: str) -> Graph:
    nodes, n = _customers(s, d)
    return generators.planted_heavy_tail(s, n, 0.3, given=nodes)[0]


def _recursive_matrix(s: SparkSession, d: str) -> Graph:
    draws, m = _orders(s, d)
    return generators.recursive_matrix(s, max(1, math.ceil(math.log2(max(1, m) / 8))), draws=draws)


def _hyperbolic(s: SparkSession, d: str) -> Graph:
    nodes, n = _customers(s, d)
    return generators.hyperbolic_disk(s, n, 8.0, nodes=nodes)


for _name, _make in {"two_density": _two_density, "heavy_tail": _heavy_tail, "recursive_matrix": _recursive_matrix, "hyperbolic": _hyperbolic}.items():
    register(f"generator_{_name}", lambda s, d, f=_make: f(s, d).edges)

# -- around the methods -----------------------------------------------------------------------------------------

register("cut_edges", lambda s, d: relational.cut_edges(*_pages(s, d)), sql.query("pagepages", select="SELECT u, v, w, a.comm cu, b.comm cv FROM e JOIN t a ON a.id = u JOIN t b ON b.id = v WHERE a.comm <> b.comm"))
register("ego_net", lambda s, d: relational.ego_net(builders.basket(s, d), 7), sql.query("basket", sql.ARCS, "nb AS (SELECT 7 id UNION SELECT dst FROM arcs WHERE src = 7)", select="SELECT u, v, w FROM e WHERE u IN (SELECT id FROM nb) AND v IN (SELECT id FROM nb)"))
register("top_members", lambda s, d: relational.top_members(*_planted(s, d), k=3), sql.query("planted", sql.VOL, select="SELECT comm, id, vol, place FROM (SELECT comm, id, vol, row_number() OVER (PARTITION BY comm ORDER BY vol DESC, id)::INT place FROM vol JOIN t USING (id)) WHERE place <= 3"))
register("size_share", lambda s, d: relational.size_share(_planted(s, d)[1]), sql.query("planted", select="SELECT comm, size, round(sum(size) OVER (ORDER BY size DESC, comm ROWS UNBOUNDED PRECEDING) / sum(size) OVER (), 6) share FROM (SELECT comm, count(*) size FROM t GROUP BY 1)"))


def _sales(s: SparkSession, d: str) -> DataFrame:
    c = load_table(s, d, "customer").select(F.col("c_custkey").alias("id"), F.col("c_mktsegment").alias("segment"))
    o = load_table(s, d, "orders").select(F.col("o_custkey").alias("id"), (F.col("o_totalprice") * 100).cast("decimal(20,0)").cast("long").alias("cents"))
    return relational.attach(builders.geo_truth(s, d), o.join(c, "id"), "id")


for _how in ("rollup", "cube"):
    register(f"{_how}_communities", lambda s, d, h=_how: relational.grouped(_sales(s, d), ["comm", "segment"], F.sum("cents"), h), sql.query("geo", select=f"SELECT comm, c_mktsegment segment, count(*) n, sum((o_totalprice * 100)::DECIMAL(20, 0)::BIGINT)::BIGINT total FROM orders JOIN customer ON c_custkey = o_custkey JOIN t ON t.id = c_custkey GROUP BY {_how.upper()}(comm, c_mktsegment)"))


def _snapshots(s: SparkSession, d: str) -> DataFrame:
    users = load_table(s, d, "events").select(F.col("user_id").alias("id")).distinct()
    days = F.array(*(F.to_timestamp(F.lit(f"2024-01-{k:02}")) for k in (5, 15, 25)))
    return users.select("id", F.posexplode(days).alias("k", "ts")).select("id", "ts", ((F.col("id") + F.col("k")) % 5).cast("long").alias("comm"))


register("asof_community", lambda s, d: relational.asof_community(load_table(s, d, "events"), _snapshots(s, d)), """WITH sn AS (SELECT DISTINCT user_id id, k, (DATE '2024-01-05' + (k * 10)::INT)::TIMESTAMP ts, (user_id + k) % 5 comm FROM events, (SELECT unnest([0, 1, 2]) k))
SELECT event_id, user_id, comm FROM (SELECT event_id, user_id, comm, row_number() OVER (PARTITION BY event_id ORDER BY sn.ts DESC NULLS LAST) r FROM events LEFT JOIN sn ON sn.id = user_id AND sn.ts <= events.ts) WHERE r = 1""")
register("interval_coactivity", lambda s, d: relational.interval_edges(load_table(s, d, "events"), 600), "SELECT a.user_id u, b.user_id v, count(*) w FROM events a JOIN events b ON a.event_type = b.event_type AND a.user_id < b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 600000000 GROUP BY 1, 2")


def _halves(s: SparkSession, d: str) -> tuple[Graph, Graph]:
    li = load_table(s, d, "lineitem")
    early = F.col("l_shipdate") < "1998-06-01"
    make = lambda rows: builders.cooccurrence(rows.select("l_orderkey", "l_suppkey"), "l_orderkey", "l_suppkey")
    return make(li.where(early)), make(li.where(~early))


_HALF = """d AS (SELECT DISTINCT l_shipdate < TIMESTAMP '1998-06-01' early, l_orderkey k, l_suppkey i FROM lineitem), p AS (SELECT DISTINCT a.early, a.i u, b.i v FROM d a JOIN d b ON a.early = b.early AND a.k = b.k AND a.i < b.i)"""
register("edge_snapshot_except", lambda s, d: relational.lost_edges(*_halves(s, d)), f"WITH {_HALF} SELECT u, v FROM p WHERE early EXCEPT SELECT u, v FROM p WHERE NOT early")
register("edge_snapshot_intersect", lambda s, d: relational.common_edges(*_halves(s, d)), f"WITH {_HALF} SELECT u, v FROM p WHERE early INTERSECT SELECT u, v FROM p WHERE NOT early")

#: Measured rows from orders: a priority stands for a method, a status for a graph, the orders for seconds and the share of large ones for modularity.
_BASE = "1-URGENT"
_MET = f"met AS (SELECT o_orderpriority algo, o_orderstatus graph, count(*)::DOUBLE AS seconds, count(*) FILTER (o_totalprice >= 100000)::DOUBLE / count(*)::DOUBLE AS modularity FROM orders GROUP BY 1, 2), b AS (SELECT graph, seconds bs, modularity bq FROM met WHERE algo = '{_BASE}')"
_SC = "sc AS (SELECT algo, round(exp(avg(ln(seconds / bs))), 4) time_score, round(avg(modularity - bq), 4) modularity_score FROM met JOIN b USING (graph) GROUP BY 1)"


def _metrics(s: SparkSession, d: str) -> DataFrame:
    n = F.count("*").cast("double")
    return load_table(s, d, "orders").groupBy(F.col("o_orderpriority").alias("algo"), F.col("o_orderstatus").alias("graph")).agg(n.alias("seconds"), (F.count_if(F.col("o_totalprice") >= 100_000).cast("double") / n).alias("modularity"))


register("quality_vs_baseline", lambda s, d: score_table.quality_vs_baseline(_metrics(s, d), _BASE), f"WITH {_MET} SELECT algo, graph, round(seconds / bs, 6) time_ratio, round(modularity - bq, 6) modularity_delta FROM met JOIN b USING (graph)")
register("scores", lambda s, d: score_table.scores(_metrics(s, d), _BASE), f"WITH {_MET}, {_SC} SELECT * FROM sc")
register("pareto", lambda s, d: score_table.pareto(score_table.scores(_metrics(s, d), _BASE)), f"WITH {_MET}, {_SC} SELECT * FROM sc WHERE NOT EXISTS (SELECT 1 FROM sc o WHERE o.time_score <= sc.time_score AND o.modularity_score >= sc.modularity_score AND (o.time_score < sc.time_score OR o.modularity_score > sc.modularity_score))")

# -- samples and the SQL surface ----------------------------------------------------------------------------------

_KEPT = "((({0} % 2147483647) * 48271 + 5) % 2147483647) % 1000 < {1}".format
_EDGE = "(({0} % 1000003) * 1009 + {1} % 1000003)".format
register("sample_nodes", lambda s, d: sampling.sample_nodes(builders.basket(s, d), 300, 5).edges, sql.query("basket", select=f"SELECT u, v, w FROM e WHERE {_KEPT('u', 300)} AND {_KEPT('v', 300)}"))
register("sample_edges", lambda s, d: sampling.sample_edges(builders.basket(s, d), 100, 5).edges, sql.query("basket", select=f"SELECT u, v, w FROM e WHERE {_KEPT(_EDGE('u', 'v'), 100)}"))
register("sample_spread", lambda s, d: sampling.spread_from((g := builders.basket(s, d)), g.nodes.where("id <= 3"), 2, 200, 5),
         sql.query("basket", sql.ARCS, f"f AS (SELECT src, dst FROM arcs WHERE {_KEPT(_EDGE('src', 'dst'), 200)}), h0 AS (SELECT id FROM n WHERE id <= 3), h1 AS (SELECT dst id FROM f WHERE src IN (FROM h0)), h2 AS (SELECT dst id FROM f WHERE src IN (FROM h1))",
                   select="SELECT id, min(hop)::INT hop FROM (SELECT id, 0 hop FROM h0 UNION ALL SELECT id, 1 FROM h1 UNION ALL SELECT id, 2 FROM h2) GROUP BY id"))


def _from_views(s: SparkSession, d: str) -> DataFrame:
    surface.publish(s, "geo", *_geo(s, d))
    return s.sql("SELECT comm, count(*) size, sum(w) inner_w FROM geo_communities c JOIN geo_edges e ON c.id = e.u GROUP BY comm")


def _from_lines(s: SparkSession, d: str) -> DataFrame:
    surface.register_functions(s)
    rows = builders.supply(s, d).edges.groupBy("u", F.floor(F.col("v") / 64)).agg(  # at most 64 neighbours a line
        F.array_join(F.sort_array(F.collect_list("v")), " ").alias("others")
    )
    rows.select(F.concat_ws(": ", "u", "others").alias("line")).createOrReplaceTempView("supply_lines")
    return s.sql("SELECT t.u, t.v FROM supply_lines, LATERAL explode_adjacency(line) t")


register("sql_views", _from_views, sql.query("geo", select="SELECT comm, count(*) size, sum(w)::BIGINT inner_w FROM t JOIN e ON t.id = e.u GROUP BY comm"))
register("adjacency_lines", _from_lines, sql.query("supply", select="SELECT u, v FROM e"))

# -- streams ------------------------------------------------------------------------------------------------------

register("stream_user_state", lambda s, d: streaming.latest(streaming.drain(streaming.user_state(streaming.read_stream(s, f"{d}/events.parquet")), "users")),
         "SELECT user_id, n, l.event_id last_event, l.event_type last_type FROM (SELECT user_id, count(*) n, max({'ts': ts, 'event_id': event_id, 'event_type': event_type}) l FROM events GROUP BY 1)")
register("stream_activity", lambda s, d: streaming.drain(streaming.stream_activity(streaming.read_stream(s, f"{d}/events.parquet")), "activity"))


from shoal import workloads  # noqa: E402

for _name, _run in workloads.QUERIES.items():
    register(_name, _run, workloads.ORACLES.get(_name))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Communities of near-duplicate documents, with their sizes."""
    found = propagation.propagate_labels(builders.neardup_all(spark, sf_dir))
    return found.join(quality.community_sizes(found), "comm").select("id", "comm", "size")
