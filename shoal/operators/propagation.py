"""Label propagation: each node takes the label of greatest total weight around it.

A round is cut into sub-rounds ("slots", by an arithmetic hash of node, round and seed): nodes of one
slot change together, later slots see their labels. One slot is the synchronous method, which swaps
labels for ever on bipartite graphs (a repeated assignment stops it).

Physical plan of a sub-round. State small enough (`BROADCAST_NODES`, or state='broadcast'): it is broadcast to
arcs that lie as arrays in parts of whole nodes (`parts`; for scores beyond 63 bits, joined to arcs by
source), and nothing is shuffled. Otherwise (state='shuffle') the
label join shuffles by target and sums travel combined. Small graphs run in one task (`onetask`), unless a
state is asked for. The winner is a maximum of one packed decimal, which stays a hash
aggregate; where weights or ids do not fit its digits, it is a maximum of a struct.

Several runs (`propagate_batch`) go at the same time on parts that are cut once; where state is shuffled they are one more key
and share each scan of the arcs.
"""

from __future__ import annotations

import math
import time
import warnings
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from shoal.core.graph import Graph, canonical, singletons
from shoal.core.storage import Scratch
from shoal.functions.scalar import label_hash, slot
from shoal.operators import onetask, parts

#: Nodes (times runs) whose labels are broadcast.
BROADCAST_NODES = 2_000_000
#: Packed winners hold labels from 0 up to this, and (ties='hash') weight sums up to 10^9.
_BASE, _HASH_WEIGHT = 10**18, 10**9
_ROW = {"level": 0, "phase": "lp", "round": 0, "slot": 0, "updated": 0, "active": 0, "seconds": 0.0}


@dataclass
class RunLog:
    """Rows (level, phase, round, slot, updated, active, seconds) of a run; `settled` tells whether it ended by its own
    stop rule (None before the end)."""

    rows: list[dict] = field(default_factory=list)
    settled: bool | None = None

    def add(self, **row) -> None:
        self.rows.append({**_ROW, **row})

    def frame(self, spark) -> DataFrame:
        return spark.createDataFrame([tuple(r[k] for k in _ROW) for r in self.rows], "level int, phase string, round int, slot int, updated long, active long, seconds double")


def _key(ties: str, seed: int | Column) -> Column:
    base, comm = F.lit(str(_BASE)).cast("decimal(38,0)"), F.col("comm").cast("decimal(38,0)")
    weight = F.col("w").cast("decimal(19,0)")
    if ties == "keep_min":
        weight = (F.lit(2).cast("decimal(1,0)") * weight + F.col("own").cast("long").cast("decimal(1,0)")).cast("decimal(20,0)")
    elif ties == "hash":
        weight = (weight * F.lit(10_000_000_000).cast("decimal(11,0)") - label_hash(F.col("comm"), seed).cast("decimal(10,0)")).cast("decimal(20,0)")
    return (weight * base - comm).cast("decimal(38,0)")


def _struct(ties: str, seed: int | Column) -> Column:
    """The same order without bounds on weights and labels."""
    first = {"keep_min": F.col("own").cast("long"), "min": F.lit(0).cast("long"), "hash": -label_hash(F.col("comm"), seed).cast("long")}[ties]
    return F.struct("w", first.alias("t"), (-F.col("comm")).alias("nc"))


def label_weights(arcs: DataFrame, state: DataFrame, evaluated: Column | None = None, weighted: bool = True, broadcast: bool = False, keys: tuple[str, ...] = ()) -> DataFrame:
    """(id, own label, comm, w): the weight of every label around each evaluated node; for each value of `keys`."""
    own = state if evaluated is None else state.where(evaluated)
    own, other = own.select(*keys, F.col("id").alias("src"), F.col("comm").alias("mine")), state.select(*keys, F.col("id").alias("dst"), "comm")
    if broadcast:
        own, other = F.broadcast(own), F.broadcast(other)
    near = arcs.join(own, "src").join(other, [*keys, "dst"])
    sums = near.groupBy(*keys, "src", "mine", "comm").agg((F.sum("w") if weighted else F.count("*")).alias("w"))
    return sums.select(*keys, F.col("src").alias("id"), "mine", "comm", "w", (F.col("mine") == F.col("comm")).alias("own"))


def dominant_labels(weights: DataFrame, ties: str = "keep_min", seed: int | Column = 0, keys: tuple[str, ...] = (), wide: bool = False) -> DataFrame:
    """(id, mine, to): the winner of each node. `wide` is for weights or labels beyond the packed key."""
    if ties not in ("keep_min", "min", "hash"):
        raise ValueError(f"ties must be keep_min, min or hash, not {ties}")
    if wide:
        return weights.groupBy(*keys, "id", "mine").agg(F.max(_struct(ties, seed)).alias("k")).select(*keys, "id", "mine", (-F.col("k.nc")).alias("to"))
    best = weights.withColumn("key", _key(ties, seed)).groupBy(*keys, "id", "mine").agg(F.max("key").alias("key"))
    base = F.lit(str(_BASE)).cast("decimal(38,0)")
    below = F.pmod(F.col("key"), base)
    return best.select(*keys, "id", "mine", F.when(below == 0, F.lit(0)).otherwise(base - below).cast("long").alias("to"))


def lp_step(arcs: DataFrame, state: DataFrame, evaluated: Column | None = None, ties: str = "keep_min", seed: int = 0, weighted: bool = True, broadcast: bool = False) -> DataFrame:
    """One sub-round as a pure plan: the assignment after it."""
    winner = dominant_labels(label_weights(arcs, state, evaluated, weighted, broadcast), ties, seed).select("id", "to")
    return state.join(F.broadcast(winner) if broadcast else winner, "id", "left").select("id", F.coalesce("to", "comm").alias("comm"))


def majority_violations(g: Graph, assignment: DataFrame) -> DataFrame:
    """Nodes whose label is not one of greatest weight around them: (id, comm, w, best)."""
    w = label_weights(g.arcs, assignment)
    best = w.groupBy("id", F.col("mine").alias("comm")).agg(F.max("w").alias("best"), F.coalesce(F.max(F.when(F.col("own"), F.col("w"))), F.lit(0).cast("long")).alias("w"))
    return best.where("w < best")


@dataclass
class Size:
    nodes: int
    low: int
    high: int
    edges: int
    weight: int
    by_class: bool = False

    @property
    def small(self) -> bool:
        """Whether one task takes the graph; one held by its classes always fits."""
        return self.by_class or onetask.fits(2 * self.edges, self.weight, self.low)


def size_of(g: Graph) -> Size:
    twins = g.held_twins
    if twins is not None:
        return Size(twins.nodes, twins.low, twins.high, twins.pairs, twins.weight, True)
    ids = g.nodes.agg(F.count("*"), F.min("id"), F.max("id")).first()
    weight = g.edges.agg(F.count("*"), F.sum("w")).first()
    return Size(ids[0], ids[1] or 0, ids[2] or 0, weight[0], weight[1] or 0)


def by_parts(size: Size, state: str = "auto", gamma: tuple[int, int] = (0, 0)) -> bool:
    """Whether a graph that is not small has its state broadcast to parts."""
    return not size.by_class and (state == "broadcast" or (state == "auto" and size.nodes <= BROADCAST_NODES)) and parts.takes(size.low, size.weight, gamma)


def in_parts(g: Graph, scratch: Scratch, size: Size | None = None) -> Graph:
    """The graph with its arcs cut into parts, unless they are already."""
    size = size or size_of(g)
    return g if g.parts is not None else Graph(g.edges, g.nodes, g.twins, parts.cut(g.edges, g.nodes, size.edges, size.weight, scratch))


def propagate_labels(g: Graph, *, rename: bool = True, start: DataFrame | None = None, active: DataFrame | None = None, **options) -> DataFrame:
    """Communities by label propagation: (id, comm), by default with canonical names.

    start and active resume from a given state; the other options are those of `propagate_batch`."""
    found = _propagate(g, start, active, (), 1, **options)
    return canonical(found) if rename else found


def propagate_batch(g: Graph, runs: int, **options) -> DataFrame:
    """(run, id, comm) of several runs with consecutive seeds, each as `propagate_labels` would give it. Runs on small graphs, or
    on parts that are cut once, go at the same time; otherwise every sub-round scans the arcs once for all runs that have not ended."""
    state, size = options.get("state", "auto"), size_of(g)
    alone = state in ("auto", "task") and size.small
    if not alone and by_parts(size, state):
        g, alone = in_parts(g, Scratch(g.spark, "batch"), size), True
    if alone:
        seed, log = options.pop("seed", 0), options.pop("log", None)
        logs = [RunLog() for _ in range(runs)]
        with ThreadPoolExecutor(min(runs, 4)) as pool:  # each run is one task, or reads the same parts
            found = list(pool.map(lambda i: propagate_labels(g, seed=seed + i, log=logs[i], **options), range(runs)))
        if log is not None:
            log.rows += [row for one in logs for row in one.rows]
            log.settled = all(one.settled for one in logs) and log.settled in (None, True)
        return reduce(DataFrame.unionAll, [f.select(F.lit(i).alias("run"), "id", "comm") for i, f in enumerate(found)])
    start = singletons(g).select(F.explode(F.array(*(F.lit(i) for i in range(runs)))).alias("run"), "id", "comm")
    found = _propagate(g, start, None, ("run",), runs, **options)
    names = found.groupBy("run", "comm").agg(F.min("id").alias("name"))
    return found.join(names, ["run", "comm"]).select("run", "id", F.col("name").alias("comm"))


def _propagate(
    g: Graph, start: DataFrame | None, active: DataFrame | None, keys: tuple[str, ...], runs: int, *, theta: float | None = None, theta_frac: float = 1e-5, schedule: str = "semi", slots: int = 2, rotate: bool = True,
    ties: str = "keep_min", weighted: bool = True, frontier: bool = True, stop: str = "theta", max_rounds: int = 100, seed: int = 0, log: RunLog | None = None, balance: str = "arcs", state: str = "auto",
) -> DataFrame:
    """The loop. Rounds go on while more than theta nodes change (theta: by default nodes times theta_frac).

    schedule: 'sync' (one slot), 'semi' (slots by hash, new ones each round if `rotate`), 'random' (many
    slots in a seeded order). frontier: nodes sleep until a neighbour changes. stop='majority' ends when
    every node holds a label of greatest weight. state: 'task', 'broadcast', 'shuffle', or 'auto' by size. balance='arcs' splits a hub's arcs over tasks where state is shuffled. A run that reaches
    max_rounds first says so in log.settled and by a warning.
    """
    log, scratch = log if log is not None else RunLog(), Scratch(g.spark, "lp")
    if ties not in ("keep_min", "min", "hash"):
        raise ValueError(f"ties must be keep_min, min or hash, not {ties}")
    size = size_of(g)
    n, wide = size.nodes, size.low < 0 or size.high >= _BASE or (ties == "hash" and 2 * size.weight >= _HASH_WEIGHT)
    theta = n * theta_frac if theta is None else theta
    slots = {"sync": 1, "semi": slots, "random": max(slots, 8)}[schedule]
    options = {"theta": theta, "schedule": schedule, "slots": slots, "rotate": rotate, "ties": ties, "weighted": weighted, "frontier": frontier, "stop": stop, "max_rounds": max_rounds, "seed": seed}
    if not keys and (state == "task" or (state == "auto" and size.small)):
        found, _ = onetask.run(g, scratch, lambda small, comm, on: onetask.propagate(small, comm, on, **options), log, start, active)
        _warn(log, theta, max_rounds)
        return found
    broadcast = state == "broadcast" or (state == "auto" and n * runs <= BROADCAST_NODES)
    if broadcast and not keys and parts.takes(size.low, size.weight):
        held = g.parts or parts.cut(g.edges, g.nodes, size.edges, size.weight, scratch)
        begin = held.state(start, active)
        if held.alone:
            found, (rows, log.settled) = parts.in_one_task(held, scratch, lambda one: onetask.propagate(one, *begin, **options))
        else:
            found, rows, log.settled = onetask.propagate(held, *begin, **options)
            found = held.written(scratch, found)
        for row in rows:
            log.add(**row)
        _warn(log, theta, max_rounds)
        return found
    start = start if start is not None else singletons(g)
    arcs = g.arcs.repartition("src", "dst") if balance == "arcs" and not broadcast else g.arcs.repartition("src")
    arcs = arcs.persist()
    on = F.lit(True) if active is None else F.coalesce("on", F.lit(False))
    begin = start if active is None else start.join(active.select("id", F.lit(True).alias("on")), "id", "left")
    begin = begin.select(*keys, "id", "comm", on.alias("active"))
    now = scratch.write(begin)
    own_seed = F.lit(seed).cast("long") + F.col("run") if keys else seed
    live, seen = list(range(runs)), []
    run = F.col("run") if keys else F.lit(0)
    log.settled = False
    try:
        for round_no in range(1, max_rounds + 1):
            updated = dict.fromkeys(live, 0)
            for s in range(slots):
                began = time.time()
                chosen = F.lit(True) if slots == 1 else slot(F.col("id"), round_no if rotate else 0, slots, own_seed) == s
                if len(live) < runs:
                    chosen = chosen & run.isin(live)
                evaluated = chosen & F.col("active") if frontier else chosen
                winner = dominant_labels(label_weights(arcs, now, evaluated, weighted, broadcast, keys), ties, own_seed, keys, wide)
                counts = Observation()
                moved = scratch.write(winner.where("to <> mine").select(*keys, "id", "to").observe(counts, *(F.count_if(run == i).alias(f"n{i}") for i in live)))
                after = now.join(F.broadcast(moved) if broadcast else moved, [*keys, "id"], "left")
                if frontier:
                    # sleepers leave first, then the changed and their neighbours wake
                    source = moved.select(*keys, F.col("id").alias("src"))
                    near = arcs.join(F.broadcast(source) if broadcast else source, "src").select(*keys, F.col("dst").alias("id")).union(moved.select(*keys, "id")).distinct().withColumn("woken", F.lit(True))
                    after = after.join(near, [*keys, "id"], "left").withColumn("next", F.coalesce("woken", F.col("active") & ~evaluated))
                else:
                    after = after.withColumn("next", F.col("active"))
                used = Observation()
                after = after.observe(used, F.count_if(evaluated).alias("n"))
                before, now = now, scratch.write(after.select(*keys, "id", F.coalesce("to", "comm").alias("comm"), F.col("next").alias("active")))
                scratch.drop(before, moved)
                for i in live:
                    updated[i] += counts.get[f"n{i}"]
                log.add(phase="lp", round=round_no, slot=s, updated=sum(counts.get[f"n{i}"] for i in live), active=used.get["n"], seconds=time.time() - began)
            live = [i for i in live if updated[i] > theta]
            if live and stop == "majority" and not keys and majority_violations(g, now.select("id", "comm")).isEmpty():
                live = []
            if not live:
                log.settled = True
                break
            if schedule == "sync" and not keys:
                mark = now.agg(F.sum(F.xxhash64("id", "comm").cast("decimal(38,0)"))).first()[0]
                if mark in seen[-4:]:
                    log.add(phase="cycle", round=round_no)
                    break
                seen.append(mark)
        _warn(log, theta, max_rounds)
        return now.select(*keys, "id", "comm")
    finally:
        arcs.unpersist()


def _warn(log: RunLog, theta: float, max_rounds: int) -> None:
    if not log.settled and theta >= 0 and not any(r["phase"] == "cycle" for r in log.rows):
        warnings.warn(f"label propagation not settled after {max_rounds} rounds", RuntimeWarning, stacklevel=4)


def expected_theta(n: int, frac: float = 1e-5) -> int:
    """The largest number of updates that still ends a run."""
    return math.floor(n * frac)
