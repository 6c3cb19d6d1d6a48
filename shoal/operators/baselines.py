"""Methods to compare with: agglomeration by pairs, and serial methods.

Agglomeration is distributed. The serial ones (a node at a time, or a merge at a time) cannot be spread;
they run in one task whatever the graph's size, and warn above `MAX_ARCS` arcs.
"""

from __future__ import annotations

import random
import warnings
from collections import defaultdict
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shoal.core.graph import Graph, canonical, contract, lift, singletons
from shoal.core.storage import Scratch
from shoal.operators.ensemble import consensus_core
from shoal.operators.moves import modularity_of
from shoal.operators import onetask
from shoal.operators.propagation import RunLog, propagate_labels, size_of
from shoal.operators.twins import TwinGraph

#: Arcs above which a serial method warns that one task holds them all (some 200 bytes each).
MAX_ARCS = 5_000_000
#: Arcs of a graph up to which several serial runs may work at once.
LIGHT_ARCS = 500_000


def original_label_propagation(g: Graph, seed: int = 0, max_rounds: int = 30) -> DataFrame:
    """Unweighted votes, random order, until every node holds a majority label."""
    return propagate_labels(g, weighted=False, schedule="random", stop="majority", theta=0, ties="hash", seed=seed, max_rounds=max_rounds)


# -- agglomeration ---------------------------------------------------------------------------------------


def merge_scores(g: Graph, total: int) -> DataFrame:
    """(c, d, score) in both directions: whole-number gain of merging two neighbours, 2 W w - vol vol."""
    vol = g.node_stats.select("id", "vol")
    rows = g.arcs.join(vol.select(F.col("id").alias("src"), F.col("vol").alias("vs")), "src").join(vol.select(F.col("id").alias("dst"), F.col("vol").alias("vd")), "dst")
    big = lambda c: c.cast("decimal(19,0)")
    score = (big(F.lit(2 * total)) * big(F.col("w"))).cast("decimal(38,0)") - (big(F.col("vs")) * big(F.col("vd"))).cast("decimal(38,0)")
    return rows.select(F.col("src").alias("c"), F.col("dst").alias("d"), score.cast("decimal(38,0)").alias("score"))


def best_partners(g: Graph, total: int) -> DataFrame:
    """(c, d, score): the best positive partner of each community. Equal scores go to the smaller unordered
    pair, so the order of pairs is total and the best pair of all is always mutual."""
    rows = merge_scores(g, total).where("score > 0")
    best = rows.groupBy("c").agg(F.max(F.struct("score", (-F.least("c", "d")).alias("a"), (-F.greatest("c", "d")).alias("b"))).alias("p"))
    return best.select("c", (-F.col("p.a") - F.col("p.b") - F.col("c")).alias("d"), F.col("p.score").alias("score"))


def pairing_step(g: Graph, total: int, pairing: str = "matching", scratch: Scratch | None = None) -> DataFrame:
    """One level's merges (id, comm). 'matching': mutual partners only. 'star': whoever points at a member of a mutual pair joins it."""
    best = (scratch or Scratch(g.spark, "partners")).write(best_partners(g, total))  # read four times
    back = best.select(F.col("c").alias("d"), F.col("d").alias("c"))
    mutual = best.join(back, ["c", "d"]).select("c", F.least("c", "d").alias("center"))
    if pairing == "star":
        join = best.join(mutual.select(F.col("c").alias("d"), "center"), "d").join(mutual.select("c"), "c", "left_anti").select("c", "center")
        mutual = mutual.union(join)
    elif pairing != "matching":
        raise ValueError(f"pairing must be matching or star, not {pairing}")
    return canonical(g.nodes.join(mutual.withColumnRenamed("c", "id"), "id", "left").select("id", F.coalesce("center", "id").alias("comm")))


def agglomerate(g: Graph, pairing: str = "star", max_levels: int = 60, state: str = "auto", log: RunLog | None = None) -> DataFrame:
    """Merges pairs of positive gain level by level; keeps the level of highest modularity. state='shuffle' keeps small
    graphs distributed too."""
    log, scratch, size = log if log is not None else RunLog(), Scratch(g.spark, "agglomerate"), size_of(g)
    total = size.weight
    if state == "auto" and size.small:
        return onetask.run(g, scratch, lambda small, comm, on: onetask.agglomerate(small, kind=pairing, max_levels=max_levels), log)[0]
    now, solution = g, scratch.write(singletons(g))
    best, quality = solution, modularity_of(g, solution, total) if total else 0.0
    for _ in range(max_levels if total else 0):
        step = scratch.write(pairing_step(now, total, pairing, scratch))
        if step.where("id <> comm").isEmpty():
            break
        small, mapping = contract(now, step)
        now = Graph(scratch.write(small.edges), scratch.write(small.nodes))
        solution = scratch.write(lift(solution.select("id", F.col("comm").alias("super")), mapping.select("id", F.col("super").alias("comm"))))
        after = modularity_of(g, solution, total)
        if after >= quality:
            best, quality = solution, after
    return canonical(best)


# -- serial methods --------------------------------------------------------------------------------------


def _serial(g: Graph, solve: Callable[[dict[int, dict[int, int]], dict[int, int], list[int]], dict[int, int]], by_class: Callable[[TwinGraph], np.ndarray]) -> DataFrame:
    """Runs `solve(neighbours, loops, nodes)` in one task; `by_class(graph)`, which gives the same, where the graph is held by
    its classes."""
    if g.held_twins is not None:
        return canonical(onetask.run(g, Scratch(g.spark, "serial"), lambda small, comm, on: (by_class(small), [], True), RunLog())[0])
    arcs = g.arcs.count()
    if arcs > MAX_ARCS:
        warnings.warn(f"{arcs} arcs: a serial method holds them in one task", RuntimeWarning, stacklevel=3)
    one = F.lit(0).alias("g")
    rows = g.edges.select("u", "v", "w").union(g.nodes.select("id", "id", F.lit(0).cast("long"))).select(one, "*")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        near: dict[int, dict[int, int]] = defaultdict(dict)
        loops: dict[int, int] = defaultdict(int)
        for u, v, w in sorted(zip(pdf["u"].tolist(), pdf["v"].tolist(), pdf["w"].tolist(), strict=True)):
            if u == v:
                loops[u] += w
                near[u]
            else:
                near[u][v] = near[u].get(v, 0) + w
                near[v][u] = near[v].get(u, 0) + w
        found = solve(near, loops, sorted(near))
        return pd.DataFrame({"id": list(found), "comm": list(found.values())}, dtype="int64")

    return canonical(rows.groupBy("g").applyInPandas(run, "id long, comm long"))


def _node_at_a_time(near, loops, nodes, seed: int) -> dict[int, int]:
    """Move each node to the best community beside it, volumes always fresh; contract and repeat."""
    rng, place = random.Random(seed), {u: u for u in nodes}
    total = sum(sum(n.values()) for n in near.values()) // 2 + sum(loops.values())
    while total:
        vol = {u: sum(near[u].values()) + 2 * loops.get(u, 0) for u in near}
        comm, size = {u: u for u in near}, dict(vol)
        order, any_move, changed = sorted(near), False, True
        rng.shuffle(order)
        while changed:
            changed = False
            for u in order:
                w: dict[int, int] = defaultdict(int)
                for v, x in near[u].items():
                    w[comm[v]] += x
                own = comm[u]
                size[own] -= vol[u]
                gain = lambda c, u=u, w=w: 2 * total * w.get(c, 0) - vol[u] * size[c]
                best = max(sorted(w), key=gain, default=own)
                if gain(best) > gain(own):
                    comm[u], changed, any_move = best, True, True
                size[comm[u]] += vol[u]
        if not any_move:
            break
        small: dict[int, dict[int, int]] = defaultdict(dict)
        inner: dict[int, int] = defaultdict(int)
        for u in near:
            inner[comm[u]] += loops.get(u, 0)
            small[comm[u]]
            for v, x in near[u].items():
                if comm[u] == comm[v]:
                    inner[comm[u]] += x if u < v else 0
                else:
                    small[comm[u]][comm[v]] = small[comm[u]].get(comm[v], 0) + x
        place = {u: comm[c] for u, c in place.items()}
        near, loops = small, inner
    return place


def sequential_multilevel(g: Graph, seed: int = 0) -> DataFrame:
    """The serial multilevel method with a seeded random order of nodes."""
    return _serial(g, lambda near, loops, nodes: _node_at_a_time(near, loops, nodes, seed), lambda small: small.node_at_a_time(seed))


def _random_merges(near, loops, nodes, seed: int, k: int) -> dict[int, int]:
    """Merge the best pair around k sampled communities, to the end; cut where modularity was highest."""
    rng = random.Random(seed)
    near = {u: dict(n) for u, n in near.items()}
    total = sum(sum(n.values()) for n in near.values()) // 2 + sum(loops.values())
    if not total:
        return {u: u for u in nodes}
    vol = {u: sum(near[u].values()) + 2 * loops.get(u, 0) for u in near}
    live, at = sorted(near), {}
    at = {u: i for i, u in enumerate(live)}
    merges, gain, best, best_at, barren = [], 0, 0, 0, 0
    while len(live) > 1 and barren < 20 * len(live):
        found = None
        for c in (live[rng.randrange(len(live))] for _ in range(k)):
            for d, w in near[c].items():
                score = 2 * total * w - vol[c] * vol[d]
                if found is None or (score, -min(c, d), -max(c, d)) > found[0]:
                    found = ((score, -min(c, d), -max(c, d)), c, d)
        if found is None:
            barren += 1
            continue
        barren = 0
        score, keep, gone = found[0][0], *sorted(found[1:])
        for d, w in near.pop(gone).items():
            del near[d][gone]
            if d != keep:
                near[keep][d] = near[keep].get(d, 0) + w
                near[d][keep] = near[keep][d]
        vol[keep] += vol.pop(gone)
        i, last = at.pop(gone), live.pop()
        if last != gone:
            live[i], at[last] = last, i
        merges.append((keep, gone))
        gain += score
        if gain > best:
            best, best_at = gain, len(merges)
    root = {u: u for u in nodes}
    for keep, gone in reversed(merges[:best_at]):
        root[gone] = root[keep]
    for u in nodes:
        while root[u] != root[root[u]]:
            root[u] = root[root[u]]
    return root


def randomized_greedy(g: Graph, k: int = 2, seed: int = 0) -> DataFrame:
    """Greedy merging around randomly drawn communities."""
    return _serial(g, lambda near, loops, nodes: _random_merges(near, loops, nodes, seed, k), lambda small: small.random_merges(seed, k))


def randomized_greedy_batch(g: Graph, fraction: float = 0.5, seed: int = 0, max_rounds: int = 80, state: str = "auto") -> DataFrame:
    """The same idea in parallel: each round merges the mutual best pairs among a sampled share of communities.
    state='shuffle' keeps small graphs distributed too."""
    scratch, size = Scratch(g.spark, "greedy"), size_of(g)
    total = size.weight
    if state == "auto" and size.small:
        return onetask.run(g, scratch, lambda small, comm, on: onetask.greedy_batch(small, fraction=fraction, seed=seed, max_rounds=max_rounds), RunLog())[0]
    now, solution = g, scratch.write(singletons(g))
    best, quality = solution, modularity_of(g, solution, total) if total else 0.0
    for i in range(max_rounds if total else 0):
        drawn = F.pmod(F.xxhash64("id", F.lit(seed * 1000 + i)), F.lit(1000)) < int(1000 * fraction)
        part = now.nodes.where(drawn).select("id")
        sub = Graph(now.edges.join(part.withColumnRenamed("id", "u"), "u", "left_semi").join(part.withColumnRenamed("id", "v"), "v", "left_semi"), now.nodes)
        sub.__dict__["node_stats"] = now.node_stats
        step = scratch.write(pairing_step(sub, total, "matching", scratch))
        if step.where("id <> comm").isEmpty():
            if best_partners(now, total).isEmpty():
                break
            continue
        small, mapping = contract(now, step)
        now = Graph(scratch.write(small.edges), scratch.write(small.nodes))
        solution = scratch.write(lift(solution.select("id", F.col("comm").alias("super")), mapping.select("id", F.col("super").alias("comm"))))
        after = modularity_of(g, solution, total)
        if after >= quality:
            best, quality = solution, after
    return canonical(best)


def core_group_ensemble(g: Graph, b: int = 4, seed: int = 0, k: int = 2, iterate: bool = False, max_rounds: int = 10) -> DataFrame:
    """Cores that b randomised-greedy runs agree on, contracted, and a last run on them; with `iterate`, cores
    of the contracted graph again and again while the best run's modularity rises."""
    scratch, total = Scratch(g.spark, "cores"), g.total_weight()
    now, chain, quality = g, scratch.write(singletons(g).select("id", F.col("comm").alias("super"))), float("-inf")
    for _ in range(max_rounds if iterate else 1):
        def run(i: int, now: Graph = now) -> tuple[DataFrame, float]:
            one = scratch.write(randomized_greedy(now, k, seed + i))
            return one.select(F.lit(i).alias("run"), "id", "comm"), modularity_of(now, one, total) if total else 0.0

        # graphs held by classes, and small ones, are light enough for several runs at once
        light = now.held_twins is not None or now.arcs.count() <= LIGHT_ARCS
        with ThreadPoolExecutor(min(b, 4) if light else 1) as pool:
            done = list(pool.map(run, range(b)))
        runs, best = reduce(DataFrame.unionByName, [one for one, _ in done]), max(quality, *(value for _, value in done))
        if best <= quality:
            break
        quality = best
        small, mapping = contract(now, scratch.write(consensus_core(runs)))
        chain = scratch.write(lift(chain, mapping.select("id", F.col("super").alias("comm"))).select("id", F.col("comm").alias("super")))
        now = small.written(scratch)
    return canonical(lift(chain, randomized_greedy(now, k, seed + b)))

