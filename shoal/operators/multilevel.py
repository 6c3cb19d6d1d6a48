"""Multilevel modularity optimisation: move, contract, repeat on the small graph, lift back, refine."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame

from shoal.core.graph import Graph, canonical, contract, lift
from shoal.core.storage import Scratch
from shoal.operators import onetask
from shoal.operators.moves import gamma_of, local_move
from shoal.operators.propagation import RunLog, by_parts, in_parts, size_of

#: What the move phase of one task takes, with its defaults.
_MOVE = {"slots": 4, "guards": ("best", "singleton", "slots"), "max_rounds": 25, "min_gain": 1e-6, "seed": 0, "schedule": "slots"}


def multilevel(g: Graph, *, gamma: int | tuple[int, int] = 1, refine: bool = False, max_levels: int = 20, log: RunLog | None = None, **move) -> DataFrame:
    """Communities (id, comm). With `refine`, each level's lifted partition goes through a second move phase.

    From the level on whose graph fits one task, the rest runs there (unless a state or delta weights are asked for)."""
    log, scratch = log if log is not None else RunLog(), Scratch(g.spark, "levels")
    levels: list[tuple[Graph, DataFrame]] = []
    now, solution = g, None
    free = move.get("state", "auto") in ("auto", "task") and move.get("weights", "recompute") == "recompute"
    for level in range(max_levels):
        size = size_of(now)
        if free and (move.get("state") == "task" or size.by_class or onetask.fits(2 * size.edges, size.weight, size.low, gamma_of(gamma))):
            options = _MOVE | {k: sorted(v) if k == "guards" else v for k, v in move.items() if k in _MOVE} | {"gamma": gamma_of(gamma)}
            solution, _ = onetask.run(now, scratch, lambda small, comm, on, level=level: onetask.multilevel(small, refine=refine, max_levels=max_levels, level=level, **options), log)
            break
        if by_parts(size, move.get("state", "auto"), gamma_of(gamma)):
            now = in_parts(now, scratch, size)  # once for moves, contraction and refinement
            now.parts.alone |= g.parts is not None and g.parts.alone
        solution, moved = local_move(now, gamma=gamma, log=log, level=level, phase="move", **move)
        solution = scratch.write(solution)
        if not moved:
            break
        began = time.time()
        small, mapping = contract(now, solution)
        coarse = Graph(scratch.write(small.edges), scratch.write(small.nodes))
        levels.append((now, scratch.write(mapping)))
        log.add(level=level, phase="contract", seconds=time.time() - began)
        now = coarse
        solution = now.nodes.selectExpr("id", "id AS comm")
        if now.nodes.count() <= 1:
            break
    for level in range(len(levels) - 1, -1, -1):
        fine, mapping = levels[level]
        solution = scratch.write(canonical(lift(mapping, solution)))
        if refine:
            solution, _ = local_move(fine, solution, gamma=gamma, log=log, level=level, phase="refine", **move)
            solution = scratch.write(solution)
    return canonical(solution)
