"""Ensembles: several cheap runs, the cores they agree on, and a stronger run on the contracted graph."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shoal.core.graph import Graph, canonical, contract, lift
from shoal.core.storage import Scratch
from shoal.functions.scalar import mul33
from shoal.operators.multilevel import multilevel
from shoal.operators.propagation import by_parts, in_parts, propagate_batch, propagate_labels, size_of

Detector = Callable[..., DataFrame]
DETECTORS: dict[str, Detector] = {
    "lp": lambda g, seed=0, **k: propagate_labels(g, seed=seed, ties="hash", **k),
    "ml": lambda g, seed=0, **k: multilevel(g, seed=seed, **k),
    "mlr": lambda g, seed=0, **k: multilevel(g, refine=True, seed=seed, **k),
}


def register_detector(name: str, detector: Detector) -> None:
    DETECTORS[name] = detector


def base_runs(g: Graph, b: int, base: str | Detector, seed: int = 0, mode: str = "threads") -> DataFrame:
    """(run, id, comm) of b runs with different seeds. 'batched' gives the runs of label propagation one scan of the
    arcs a sub-round; 'threads' lets the jobs of any method share the cluster; 'serial' runs one after the other."""
    if mode == "batched":
        if base != "lp":
            raise ValueError("only label propagation runs batched")
        return propagate_batch(g, b, seed=seed, ties="hash")
    detect = DETECTORS[base] if isinstance(base, str) else base
    one = lambda i: detect(g, seed=seed + i)
    if mode == "threads":
        with ThreadPoolExecutor(min(b, 4)) as pool:
            found = list(pool.map(one, range(b)))
    else:
        found = [one(i) for i in range(b)]
    return reduce(DataFrame.unionByName, [a.select(F.lit(i).alias("run"), "id", "comm") for i, a in enumerate(found)])


def consensus_core(runs: DataFrame, method: str = "exact", scratch: Scratch | None = None) -> DataFrame:
    """(id, comm): nodes are together iff they are in all runs. 'mul33' and 'xxhash64' hash the tuple of
    communities (collisions join cores); 'exact' groups by the tuple itself."""
    tuples = runs.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("run", "comm"))).alias("r")).select("id", F.transform("r", lambda x: x["comm"]).alias("r"))
    if method == "exact":
        tuples = (scratch or Scratch(runs.sparkSession, "tuples")).write(tuples)  # read twice, and no group gathers in one task
        return tuples.join(tuples.groupBy("r").agg(F.min("id").alias("comm")), "r").select("id", "comm")
    key = {"mul33": mul33(F.col("r")), "xxhash64": F.xxhash64("r")}[method]
    return canonical(tuples.select("id", key.alias("comm")))


def ensemble(g: Graph, *, b: int = 4, base: str | Detector = "lp", final: str | Detector = "mlr", combine: str = "exact", seed: int = 0, mode: str | None = None) -> DataFrame:
    """Base runs (batched where the base is label propagation), consensus, contraction, final run, lifted back."""
    scratch = Scratch(g.spark, "ensemble")
    mode = mode or ("batched" if base == "lp" else "threads")
    core = scratch.write(consensus_core(base_runs(g, b, base, seed, mode), combine, scratch))
    small, mapping = contract(g, core)
    small = small.written(scratch)
    if g.parts is not None and g.parts.alone:  # its last run shares the cluster with others as well
        size = size_of(small)
        if by_parts(size) and not size.small:
            small = in_parts(small, scratch, size)
            small.parts.alone = True
    detect = DETECTORS[final] if isinstance(final, str) else final
    return canonical(lift(mapping, detect(small, seed=seed)))
