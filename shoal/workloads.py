"""The paper's workloads as registered queries, on graphs of the given tables and generated ones."""

from __future__ import annotations

from shoal import experiments as x
from shoal import oracle_text as sql
from shoal.graphs import builders
from shoal.sources import generators

#: Graphs with communities to find, and those that stand for graphs without any.
STRUCTURED = ["planted", "geo", "neardup", "pagelinks", "pagepages", "turns"]
SMALL = ["geo", "pagepages", "turns"]

QUERIES: dict = {}
ORACLES: dict[str, str] = {}

#: SQL of the graph table: components by a keyed recursion, clustering by closed wedges.
_PROFILE = """dg AS (SELECT id, count(src) degree FROM n LEFT JOIN arcs ON src = id GROUP BY id),
tr AS (SELECT id, count(*) t FROM (SELECT unnest([x.u, x.v, y.v]) id FROM e x JOIN e y ON y.u = x.v JOIN e z ON z.u = x.u AND z.v = y.v WHERE x.u <> x.v AND y.u <> y.v) GROUP BY 1),
cc(id, c) USING KEY (id) AS (SELECT id, id FROM n UNION SELECT a.dst, min(cc.c) FROM cc JOIN arcs a ON a.src = cc.id JOIN recurring.cc o ON o.id = a.dst WHERE cc.c < o.c GROUP BY a.dst)"""
_PROFILE_SELECT = """SELECT (SELECT count(*) FROM n) n, (SELECT count(*) FROM e WHERE u <> v) m, (SELECT max(degree) FROM dg) max_degree, (SELECT count(DISTINCT c) FROM cc) components,
(SELECT round(avg(round(CASE WHEN degree < 2 THEN 0 ELSE coalesce(t, 0) / (degree * (degree - 1) / 2) END, 6)), 4) FROM dg LEFT JOIN tr USING (id)) lcc"""
PROFILED = [g for g in sql.GRAPHS if g != "neardup"]


def profile_sql(graph: str) -> str:
    return sql.query(graph, sql.ARCS, _PROFILE, select=_PROFILE_SELECT).replace("WITH ", "WITH RECURSIVE ", 1)


for _g in PROFILED:
    QUERIES[f"profile_{_g}"] = lambda s, d, g=_g: x.profiles(s, d, [g]).drop("graph")
    ORACLES[f"profile_{_g}"] = profile_sql(_g)


def _basket(s, d):
    return x.suite(s, d).graph("basket")


def _contraction(s, d):
    g, t = builders.planted(s, d)
    return x.contraction_control(g, t.join(g.nodes, "id", "left_semi"))


QUERIES |= {
    "w1_profiles": lambda s, d: x.profiles(s, d),
    "w2_lp_all_graphs": lambda s, d: x.against_multilevel(s, d, ["LP"]),
    "w3_lp_strong_scaling": lambda s, d: x.strong_scaling(s, _basket(s, d), "LP"),
    "w4_lp_rounds": lambda s, d: x.rounds(s, d, ["basket", "geo", "hosts", "planted"]),
    "w5_multilevel_all_graphs": lambda s, d: x.against_multilevel(s, d, ["ML"]),
    "w6_slot_deviations": lambda s, d: x.slot_deviations(s, d, SMALL),
    "w7_move_strong_scaling": lambda s, d: x.strong_scaling(s, _basket(s, d), "move"),
    "w8_refined_all_graphs": lambda s, d: x.against_multilevel(s, d, ["MLR"]),
    "w8_phases": lambda s, d: x.phases(s, d, ["basket", *STRUCTURED]),
    "w9_ensemble_all_graphs": lambda s, d: x.against_multilevel(s, d, ["ENS", "LP"]),
    "w10_competitors": lambda s, d: x.against_multilevel(s, d, list(x.COMPETITORS), ["geo", "pagelinks", "pagepages", "turns"]),
    "w11_scores": lambda s, d: x.measured_scores(s, d, SMALL),
    "w12_mixing": lambda s, d: x.mixing(s, d, list(x.OWN)),
    "w12_heavy_tail": lambda s, d: x.heavy_tail(s, 20_000, ["LP", "ML", "MLR"]),
    "w13_massive": lambda s, d: x.massive(s, generators.recursive_matrix(s, 14, 16), list(x.OWN)),
    "w13_basket": lambda s, d: x.against_multilevel(s, d, list(x.OWN), ["basket"]),
    "w14_weak_scaling": lambda s, d: x.weak_scaling(s),
    "w15_resolution": lambda s, d: x.resolution(s, d, ["neardup", "pagepages", "pagelinks"]),
    "w15_similarity": lambda s, d: x.similarity(s, d, "pagepages", [*x.OWN, "SEQ", "AGG-S"]),
    "w15_community_graph": lambda s, d: x.community_graph_of(s, d, "pagepages", "MLR"),
    "w16_lean_dense": lambda s, d: x.lean_against_dense(s, _basket(s, d)),
    "w17_gamma_sweep": lambda s, d: x.gamma_sweep(s, {"ring": generators.ring_of_cliques(s, 30, 5), "planted": builders.planted(s, d)[0]}),
    "w18_ablations": lambda s, d: x.ablations(s, d, ["geo", "planted"]),
    "costs": lambda s, d: x.costs(s, d, "planted"),
    "contract_one_task": _contraction,
}
ORACLES["contract_one_task"] = sql.query("planted", sql.contracted("e", "t", "g1"), select="SELECT u, v, w FROM g1")
