"""Local moves that raise modularity, with exact whole-number scores.

The change of modularity when node u leaves C for D, times 2 q W^2 (W the graph's weight, resolution
p/q), is the whole number  2 q W (w(u,D) - w(u,C without u)) + p vol(u) (vol(C without u) - vol(D)).
Its sign and its maximum are exact; decimals of 38 digits hold it.

Nodes of one slot move together on data of the moment before; guards keep that from oscillating: slots,
single nodes join only towards the smaller name (before the best is chosen), the best assignment seen is
kept, ties go to the smaller community.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from shoal.core.graph import Graph, canonical, singletons
from shoal.core.storage import Scratch
from shoal.functions.scalar import slot
from shoal.operators import lean, onetask, parts
from shoal.operators.propagation import BROADCAST_NODES, RunLog, size_of

Gamma = int | tuple[int, int]


def gamma_of(gamma: Gamma) -> tuple[int, int]:
    return gamma if isinstance(gamma, tuple) else (gamma, 1)


def community_volume(g: Graph, assignment: DataFrame) -> DataFrame:
    """(comm, vol, size)."""
    return g.node_stats.join(assignment, "id").groupBy("comm").agg(F.sum("vol").alias("vol"), F.count("*").alias("size"))


def weight_to_communities(g: Graph, assignment: DataFrame, arcs: DataFrame | None = None) -> DataFrame:
    """(id, comm, w): weight from each node to each community around it, loops left out."""
    return (arcs if arcs is not None else g.arcs).join(assignment.select(F.col("id").alias("dst"), "comm"), "dst").groupBy(F.col("src").alias("id"), "comm").agg(F.sum("w").alias("w"))


def move_scores(g: Graph, assignment: DataFrame, total: int, gamma: Gamma = 1, *, weights: DataFrame | None = None, volumes: DataFrame | None = None, broadcast: bool = False) -> DataFrame:
    """(id, from_comm, to_comm, score, single_from, single_to) for every node and every other community around it."""
    p, q = gamma_of(gamma)
    hint = F.broadcast if broadcast else (lambda d: d)
    w = weights if weights is not None else weight_to_communities(g, assignment)
    volumes = volumes if volumes is not None else community_volume(g, assignment)
    own = assignment.join(g.node_stats.select("id", F.col("vol").alias("vol_u")), "id").select("id", F.col("comm").alias("from_comm"), "vol_u")
    inner = w.join(hint(own), "id")
    mine = inner.where("comm = from_comm").select("id", F.col("w").alias("w_own"))
    source = volumes.select(F.col("comm").alias("from_comm"), F.col("vol").alias("vol_from"), F.col("size").alias("size_from"))
    target = volumes.select(F.col("comm").alias("to_comm"), F.col("vol").alias("vol_to"), F.col("size").alias("size_to"))
    rows = inner.where("comm <> from_comm").withColumnRenamed("comm", "to_comm").join(mine, "id", "left").join(hint(source), "from_comm").join(hint(target), "to_comm")
    big = lambda c: F.col(c).cast("decimal(19,0)")
    pull = (F.lit(2 * q * total).cast("decimal(19,0)") * (F.col("w") - F.coalesce("w_own", F.lit(0).cast("long"))).cast("decimal(19,0)")).cast("decimal(38,0)")
    push = ((big("vol_u") * F.lit(p)).cast("decimal(19,0)") * (F.col("vol_from") - F.col("vol_u") - F.col("vol_to")).cast("decimal(19,0)")).cast("decimal(38,0)")
    return rows.select("id", "from_comm", "to_comm", (pull + push).cast("decimal(38,0)").alias("score"), (F.col("size_from") == 1).alias("single_from"), (F.col("size_to") == 1).alias("single_to"))


def best_moves(scores: DataFrame, single_guard: bool = True) -> DataFrame:
    """(id, from_comm, to_comm, score): the best positive move of each node, ties to the smaller community."""
    rows = scores.where("score > 0")
    if single_guard:
        rows = rows.where("NOT (single_from AND single_to AND to_comm > from_comm)")
    best = rows.groupBy("id", "from_comm").agg(F.max(F.struct("score", (-F.col("to_comm")).alias("nc"))).alias("b"))
    return best.select("id", "from_comm", (-F.col("b.nc")).alias("to_comm"), F.col("b.score").alias("score"))


def modularity_of(g: Graph, assignment: DataFrame, total: int, gamma: Gamma = 1) -> float:
    from shoal.measures.quality import modularity

    return float(modularity(g, assignment, gamma, total).first()["modularity"])


def local_move(
    g: Graph, start: DataFrame | None = None, *, gamma: Gamma = 1, slots: int = 4, guards: frozenset[str] | set[str] = frozenset({"slots", "singleton", "best"}), max_rounds: int = 25, min_gain: float = 1e-6,
    seed: int = 0, weights: str = "recompute", state: str = "auto", schedule: str = "slots", log: RunLog | None = None, level: int = 0, phase: str = "move", rename: bool = True,
) -> tuple[DataFrame, int]:
    """Moves nodes until stable: (assignment, number of moves).

    weights: 'recompute' sums weights to communities anew each sub-round; 'delta' keeps them in a table
    that movers update by signed rows. state: 'broadcast' sends assignment and volumes to all workers,
    'shuffle' is the memory-lean way, 'task' runs small graphs in one task; 'auto' decides by size (and keeps
    'delta' distributed). schedule='independent' moves only nodes whose priority beats that of all candidates
    around them. Without `rename`, communities keep the names that they have at the end.
    """
    log, scratch = log if log is not None else RunLog(), Scratch(g.spark, "move")
    size = size_of(g)
    total, n = size.weight, size.nodes
    options = {"gamma": gamma_of(gamma), "slots": slots, "guards": sorted(guards), "max_rounds": max_rounds, "min_gain": min_gain, "seed": seed, "schedule": schedule, "level": level, "phase": phase, "rename": rename}
    known = g.parts if parts.takes(size.low, total, gamma_of(gamma)) else None
    if state == "task" and known is not None and start is None:
        found, (count, rows, settled) = parts.in_one_task(known, scratch, lambda one: onetask.move(one, one.ids, **options))
        _log(log, rows, settled)
        return found, count
    if state == "task" or (state == "auto" and weights == "recompute" and (size.by_class or onetask.fits(2 * size.edges, total, size.low, gamma_of(gamma)))):
        found, count = onetask.run(g, scratch, lambda small, comm, on: onetask.move(small, comm, **options), log, start)
        return found, count
    broadcast = state == "broadcast" or (state == "auto" and n <= BROADCAST_NODES)
    if broadcast and parts.takes(size.low, total, gamma_of(gamma)):
        held = g.parts or parts.cut(g.edges, g.nodes, size.edges, total, scratch)
        if held.alone and weights == "recompute":
            begin = held.state(start, None)[0]
            found, (count, rows, settled) = parts.in_one_task(held, scratch, lambda one: onetask.move(one, begin, **options))
            _log(log, rows, settled)
            return found, count
        held = parts.CachedParts.of(held, scratch) if weights == "delta" else held
        found, count, rows, settled = onetask.move(held, held.state(start, None)[0], **options)
        _log(log, rows, settled)
        return held.written(scratch, found), count
    if known is not None and not broadcast and weights == "recompute" and schedule == "slots" and start is None:
        found, count, rows, settled = lean.move(known, scratch, **{k: v for k, v in options.items() if k not in ("schedule", "rename")})
        _log(log, rows, settled)
        return canonical(found) if rename else found, count
    arcs = g.arcs.repartition("src").persist()
    stats = g.node_stats.persist()
    frozen = Graph(g.edges, g.nodes)
    frozen.__dict__["arcs"], frozen.__dict__["node_stats"] = arcs, stats
    now = scratch.write(start if start is not None else singletons(g))
    slots = slots if "slots" in guards else 1
    moved_total, quality = 0, modularity_of(frozen, now, total, gamma) if total else 0.0
    best, best_quality = now, quality
    table = scratch.write(weight_to_communities(frozen, now)) if weights == "delta" else None
    settled = not total
    try:
        for round_no in range(1, max_rounds + 1 if total else 0):
            moved_round = 0
            for s in range(slots):
                began = time.time()
                scores = move_scores(frozen, now, total, gamma, weights=table if table is not None else None, broadcast=broadcast)
                chosen = scores if slots == 1 else scores.where(slot(F.col("id"), round_no, slots, seed) == s)
                moves = best_moves(chosen, "singleton" in guards)
                if schedule == "independent":
                    moves = _independent(arcs, moves, round_no, seed)
                seen = Observation()
                moves = scratch.write(moves.select("id", "from_comm", "to_comm").observe(seen, F.count("*").alias("n")))
                count = seen.get["n"]
                evaluated = n if slots == 1 else frozen.nodes.where(slot(F.col("id"), round_no, slots, seed) == s).count()
                if count:
                    before, now = now, scratch.write(now.join(moves.select("id", "to_comm"), "id", "left").select("id", F.coalesce("to_comm", "comm").alias("comm")))
                    if before is not best:
                        scratch.drop(before)
                    if table is not None:
                        change = arcs.join(moves.select(F.col("id").alias("dst"), "from_comm", "to_comm"), "dst").select(F.inline(F.array(F.struct(F.col("src").alias("id"), F.col("from_comm").alias("comm"), (-F.col("w")).alias("w")), F.struct(F.col("src").alias("id"), F.col("to_comm").alias("comm"), "w"))))
                        old, table = table, scratch.write(table.unionByName(change).groupBy("id", "comm").agg(F.sum("w").alias("w")).where("w <> 0"))
                        scratch.drop(old)
                scratch.drop(moves)
                moved_round += count
                log.add(level=level, phase=phase, round=round_no, slot=s, updated=count, active=evaluated, seconds=time.time() - began)
            moved_total += moved_round
            if not moved_round:
                settled = True
                break
            after = modularity_of(frozen, now, total, gamma)
            gain, quality = after - quality, after
            if after > best_quality or "best" not in guards:
                best, best_quality = now, after
            if gain < min_gain:
                settled = True
                break
        log.settled = settled if log.settled is None else log.settled and settled
        found = best if "best" in guards else now
        return canonical(found) if rename else found, moved_total
    finally:
        arcs.unpersist()
        stats.unpersist()


def _log(log: RunLog, rows: list[dict], settled: bool) -> None:
    for row in rows:
        log.add(**row)
    log.settled = settled if log.settled is None else log.settled and settled


def _independent(arcs: DataFrame, moves: DataFrame, round_no: int, seed: int) -> DataFrame:
    """Movers without a mover of higher priority beside them."""
    rank = lambda c: slot(F.col(c), round_no, 2_000_003, seed)
    rivals = arcs.join(moves.select(F.col("id").alias("src")), "src").join(moves.select(F.col("id").alias("dst")), "dst")
    beaten = rivals.where((rank("dst") > rank("src")) | ((rank("dst") == rank("src")) & (F.col("dst") < F.col("src")))).select(F.col("src").alias("id"))
    return moves.join(beaten, "id", "left_anti")
