"""The experiments as runnable workloads: every method on every graph, repeated and timed, and what follows from
the measurements (scores, Pareto set, phases, scaling, resolution, ablations).

A measured row is (algo, graph, n, m, seconds, edges_per_s, communities, modularity, settled, note). Seconds
are those of a complete run on a graph that is already written (a large one also cut into parts), averaged over repeats; edges_per_s is m over
them. Graphs are written once a session; rows of one session and folder are measured once and shared.

`python -m shoal.experiments scaling FOLDER` repeats the scaling runs in fresh sessions of 1, 2, 4 and 8 cores.
"""

from __future__ import annotations

import sys
import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shoal.core.graph import Graph, community_graph
from shoal.core.storage import Scratch
from shoal.graphs import builders
from shoal.measures import agreement, profile, quality
from shoal.measures import scores as score_table
from shoal.operators import baselines, ensemble, moves, multilevel, parts, propagation
from shoal.operators.propagation import RunLog
from shoal.sources import generators
from shoal.sources.tables import load_table

GRAPHS: dict[str, Callable[[SparkSession, str], Graph]] = {
    "basket": builders.basket, "trade": builders.trade, "supply": builders.supply, "cosupply": builders.cosupply, "geo": builders.geo, "planted": lambda s, d: builders.planted(s, d)[0],
    "neardup": builders.neardup_all, "pagelinks": builders.pagelinks, "pagepages": builders.pagepages, "hosts": builders.hosts_graph, "turns": builders.turns, "coactive": builders.coactive,
    "useritem": builders.useritem, "knn": lambda s, d: builders.knn_graph(load_table(s, d, "embeddings")),
}

Method = Callable[[Graph, int, RunLog], DataFrame]
OWN: dict[str, Method] = {
    "LP": lambda g, seed, log: propagation.propagate_labels(g, seed=seed, log=log),
    "ML": lambda g, seed, log: multilevel.multilevel(g, seed=seed, log=log),
    "MLR": lambda g, seed, log: multilevel.multilevel(g, refine=True, seed=seed, log=log),
    "ENS": lambda g, seed, log: ensemble.ensemble(g, b=4, seed=seed),
}
COMPETITORS: dict[str, Method] = {
    "LP original": lambda g, seed, log: baselines.original_label_propagation(g, seed),
    "SEQ": lambda g, seed, log: baselines.sequential_multilevel(g, seed),
    "AGG-S": lambda g, seed, log: baselines.agglomerate(g, "star", log=log),
    "AGG-M": lambda g, seed, log: baselines.agglomerate(g, "matching", log=log),
    "RGA": lambda g, seed, log: baselines.randomized_greedy(g, seed=seed),
    "CGE": lambda g, seed, log: baselines.core_group_ensemble(g, seed=seed),
    "CGE-I": lambda g, seed, log: baselines.core_group_ensemble(g, seed=seed, iterate=True),
}
METHODS = OWN | COMPETITORS
ROW = "algo string, graph string, n long, m long, seconds double, edges_per_s double, communities long, modularity double, settled boolean, note string"


@dataclass
class Suite:
    """Written graphs and measured rows of one session and folder."""

    spark: SparkSession
    folder: str
    repeats: int = 1
    graphs: dict[str, Graph] = field(default_factory=dict)
    lights: dict[str, Graph] = field(default_factory=dict)
    rows: dict[tuple[str, str], tuple] = field(default_factory=dict)
    found: dict[tuple[str, str], DataFrame] = field(default_factory=dict)
    logs: dict[tuple[str, str], RunLog] = field(default_factory=dict)

    def __post_init__(self) -> None:
        self.scratch = Scratch(self.spark, "experiments")

    def written(self, g: Graph) -> Graph:
        return Graph(self.scratch.write(g.edges.select("u", "v", "w")), self.scratch.write(g.nodes), g.twins)

    def graph(self, name: str) -> Graph:
        if name not in self.graphs:
            self.graphs[name] = self.written(GRAPHS[name](self.spark, self.folder))
        return self.graphs[name]

    def light(self, name: str) -> Graph:
        """The same graph for methods and measures: one held by its classes is not written edge by edge, one whose arcs lie in parts is
        cut once."""
        if name not in self.lights:
            g = self.graphs.get(name) or GRAPHS[name](self.spark, self.folder)
            if g.held_twins is not None:
                self.lights[name] = g.written(self.scratch)
            else:
                g = self.graph(name)
                size = propagation.size_of(g)
                self.lights[name] = propagation.in_parts(g, self.scratch, size) if propagation.by_parts(size) and not size.small else g
        return self.lights[name]

    def run(self, algo: str, name: str) -> tuple:
        """The measured row of one method on one graph; a method that fails fails the run."""
        at = (algo, name)
        if at not in self.rows:
            g, log = self.light(name), RunLog()
            n, m = (g.held_twins.nodes, g.held_twins.pairs) if g.held_twins is not None else (g.nodes.count(), g.edges.where("u <> v").count())
            seconds = []
            for i in range(self.repeats):
                began = time.time()
                found = self.scratch.write(METHODS[algo](g, i, log if i == 0 else RunLog()))
                seconds.append(time.time() - began)
            mean = sum(seconds) / len(seconds)
            q = quality.modularity(g, found).first()
            self.rows[at] = (algo, name, n, m, round(mean, 3), round(m / mean, 1), q["communities"], q["modularity"], log.settled, None)
            self.found[at], self.logs[at] = found, log
        return self.rows[at]

    def table(self, algos: list[str], names: list[str]) -> DataFrame:
        return self.spark.createDataFrame([self.run(a, n) for n in names for a in algos], ROW)


_SUITES: dict[tuple[str, str], Suite] = {}


def suite(spark: SparkSession, folder: str) -> Suite:
    key = (spark.sparkContext.applicationId, folder)
    if key not in _SUITES:
        _SUITES[key] = Suite(spark, folder)
    return _SUITES[key]


def against_multilevel(spark: SparkSession, folder: str, algos: list[str], names: list[str] | None = None) -> DataFrame:
    """Measured rows with time_ratio and modularity_delta against ML on the same graph."""
    rows = suite(spark, folder).table(list(dict.fromkeys(["ML", *algos])), names or list(GRAPHS))
    return rows.join(score_table.quality_vs_baseline(rows.where("seconds IS NOT NULL"), "ML"), ["algo", "graph"], "left").where(F.col("algo").isin(algos))


def measured_scores(spark: SparkSession, folder: str, names: list[str]) -> DataFrame:
    """Time score (geometric mean of ratios to ML) and modularity score (mean difference) of every method, and whether it
    is on the Pareto frontier. Every method is scored on every graph."""
    rows = suite(spark, folder).table(list(METHODS), names)
    table = Scratch(spark, "scores").write(score_table.scores(rows, "ML"))
    best = score_table.pareto(table).select("algo", F.lit(True).alias("frontier"))
    return table.join(best, "algo", "left").select("algo", "time_score", "modularity_score", F.coalesce("frontier", F.lit(False)).alias("frontier"))


def profiles(spark: SparkSession, folder: str, names: list[str] | None = None) -> DataFrame:
    """The graph table: one row a graph."""
    s = suite(spark, folder)
    return reduce(DataFrame.unionAll, [profile.profile(s.graph(n)).select(F.lit(n).alias("graph"), "*") for n in names or GRAPHS])


def rounds(spark: SparkSession, folder: str, names: list[str]) -> DataFrame:
    """(graph, round, updated, active, seconds) of label propagation."""
    s, parts = suite(spark, folder), []
    for n in names:
        s.run("LP", n)
        parts.append(s.logs["LP", n].frame(spark).where("phase = 'lp'").groupBy("round").agg(F.sum("updated").alias("updated"), F.sum("active").alias("active"), F.round(F.sum("seconds"), 4).alias("seconds")).select(F.lit(n).alias("graph"), "*"))
    return reduce(DataFrame.unionAll, parts)


def phases(spark: SparkSession, folder: str, names: list[str]) -> DataFrame:
    """(graph, phase, finest, whole, share): seconds of each phase of MLR on the finest level and on all levels."""
    s, parts = suite(spark, folder), []
    for n in names:
        s.run("MLR", n)
        parts.append(s.logs["MLR", n].frame(spark).select(F.lit(n).alias("graph"), "*"))
    rows = reduce(DataFrame.unionAll, parts).groupBy("graph", "phase").agg(F.sum(F.when(F.col("level") == 0, F.col("seconds")).otherwise(0.0)).alias("finest"), F.sum("seconds").alias("whole"))
    return rows.select("graph", "phase", F.round("finest", 4).alias("finest"), F.round("whole", 4).alias("whole"), F.round(F.when(F.col("whole") > 0, F.col("finest") / F.col("whole")), 3).alias("share"))


def slot_deviations(spark: SparkSession, folder: str, names: list[str], slots: tuple[int, ...] = (2, 4, 16, 64)) -> DataFrame:
    """Multilevel with few slots (many nodes move on stale data) up to many, against the serial method: communities, modularity, difference."""
    s, rows = suite(spark, folder), []
    for n in names:
        g, base = s.light(n), s.run("SEQ", n)
        for k in slots:
            q = quality.modularity(g, multilevel.multilevel(g, slots=k)).first()
            rows.append((n, k, q["communities"], q["modularity"], None if base[7] is None else round(q["modularity"] - base[7], 6)))
    return spark.createDataFrame(rows, "graph string, slots int, communities long, modularity double, difference double")


def mixing(spark: SparkSession, folder: str, algos: list[str], tenths: tuple[int, ...] = (1, 3, 5, 7, 8, 9)) -> DataFrame:
    """(mixing, algo, communities, modularity, edge_rand) on planted graphs with more and more edges between the blocks."""
    s = suite(spark, folder)

    def one_graph(mu: int) -> list[DataFrame]:
        name, parts = f"planted{mu}", []
        g, truth = builders.planted(spark, folder, mu)
        if name not in s.graphs:
            s.graphs[name] = s.written(g)
        g = s.light(name)
        if g.parts is not None:
            g.parts.alone = True
        truth = s.scratch.write(truth.join(g.nodes, "id", "left_semi"))
        for a in algos:
            row = s.run(a, name)
            one = agreement.edge_rand(g, s.found[a, name], truth)
            one = s.scratch.write(one.select(F.lit(mu / 10).alias("mixing"), F.lit(a).alias("algo"), F.lit(row[6]).alias("communities"), F.lit(row[7]).alias("modularity"), "edge_rand"))
            parts.append(one)
        return parts

    with ThreadPoolExecutor(min(len(tenths), 6)) as pool:  # no seconds are told, so graphs may share the cluster
        return reduce(DataFrame.unionAll, [part for parts in pool.map(one_graph, tenths) for part in parts])


def heavy_tail(spark: SparkSession, n: int, algos: list[str], mixings: tuple[float, ...] = (0.2, 0.5, 0.8)) -> DataFrame:
    """The same on generated graphs with power-law degrees and community sizes."""
    s, parts = Suite(spark, ""), []
    for mu in mixings:
        g, truth = generators.planted_heavy_tail(spark, n, mu)
        s.graphs["g"], truth = s.written(g), s.scratch.write(truth)
        for a in algos:
            found = s.scratch.write(METHODS[a](s.graphs["g"], 0, RunLog()))
            parts.append(agreement.edge_rand(s.graphs["g"], found, truth).select(F.lit(mu).alias("mixing"), F.lit(a).alias("algo"), F.lit(found.select("comm").distinct().count()).alias("communities"), "edge_rand"))
    return reduce(DataFrame.unionAll, parts)


def massive(spark: SparkSession, g: Graph, algos: list[str]) -> DataFrame:
    """Complete runs of the own methods on one large graph: seconds and edges a second."""
    s = Suite(spark, "")
    s.graphs["massive"] = s.written(g)
    return s.table(algos, ["massive"])


def _with_partitions(spark: SparkSession, p: int) -> SparkSession:
    """A session beside this one whose stages have p tasks, so p cores work at most."""
    other = spark.newSession()
    other.conf.set("spark.sql.shuffle.partitions", str(p))
    other.conf.set("spark.sql.adaptive.enabled", "false")
    return other


def strong_scaling(spark: SparkSession, g: Graph, method: str, workers: tuple[int, ...] = (1, 2, 4), max_rounds: int = 2) -> DataFrame:
    """(method, workers, seconds, speedup, same): distributed rounds on one graph with more and more tasks at once; `same`
    tells that the result does not depend on them. The graph is written and cut into parts once, before the seconds count."""
    scratch, rows, marks = Scratch(spark, "scaling"), [], []
    edges, nodes = (t if hasattr(t, "_scratch_path") else scratch.write(t) for t in (g.edges, g.nodes))
    size = propagation.size_of(Graph(edges, nodes))
    held = parts.cut(edges, nodes, size.edges, size.weight, scratch) if parts.takes(size.low, size.weight, (1, 1)) else None
    for p in workers:
        other = _with_partitions(spark, p)
        here = Graph(other.read.parquet(edges._scratch_path).coalesce(p), other.read.parquet(nodes._scratch_path).coalesce(p), parts=held and held.beside(other, p))
        began = time.time()
        if method == "LP":
            found = propagation.propagate_labels(here, state="broadcast", max_rounds=max_rounds, theta=-1)
        else:
            found, _ = moves.local_move(here, state="broadcast", slots=2, max_rounds=max_rounds)
        marks.append(found.agg(F.sum(F.xxhash64("id", "comm").cast("decimal(38,0)"))).first()[0])
        rows.append((method, p, time.time() - began))
    return spark.createDataFrame([(m, p, round(t, 3), round(rows[0][2] / t, 3), marks[i] == marks[0]) for i, (m, p, t) in enumerate(rows)], "method string, workers int, seconds double, speedup double, same boolean")


def weak_scaling(spark: SparkSession, scale: int = 10, steps: int = 3, max_rounds: int = 2) -> DataFrame:
    """(workers, n, m, seconds): graph and tasks double together, on generated hyperbolic graphs."""
    rows, scratch = [], Scratch(spark, "weak")
    for k in range(steps):
        g = generators.hyperbolic_disk(spark, 1 << (scale + k), 8.0)
        edges, nodes = scratch.write(g.edges), scratch.write(g.nodes)
        other = _with_partitions(spark, 1 << k)
        here = Graph(other.read.parquet(edges._scratch_path).coalesce(1 << k), other.read.parquet(nodes._scratch_path).coalesce(1 << k))
        m, began = edges.count(), time.time()
        propagation.propagate_labels(here, state="broadcast", max_rounds=max_rounds, theta=-1).count()
        rows.append(("LP", 1 << k, 1 << (scale + k), m, round(time.time() - began, 3)))
        began = time.time()
        moves.local_move(here, state="broadcast", slots=2, max_rounds=max_rounds)[0].count()
        rows.append(("move", 1 << k, 1 << (scale + k), m, round(time.time() - began, 3)))
    return spark.createDataFrame(rows, "method string, workers int, n long, m long, seconds double")


def resolution(spark: SparkSession, folder: str, names: list[str], algos: list[str] | None = None) -> DataFrame:
    """(graph, algo, communities, largest, median): how coarse each method's partition is. No seconds are told, so graphs and
    methods share the cluster, in rows that no measurement reads; what was measured already is not run again."""
    s = suite(spark, folder)
    beside = Suite(spark, folder, graphs=s.graphs, lights=s.lights, rows=dict(s.rows), found=dict(s.found))

    def one(n: str, a: str) -> DataFrame:
        beside.run(a, n)
        sizes = quality.community_sizes(beside.found[a, n])
        found = sizes.agg(F.count("*").alias("communities"), F.max("size").alias("largest"), F.percentile("size", 0.5).alias("median"))
        return beside.scratch.write(found.select(F.lit(n).alias("graph"), F.lit(a).alias("algo"), "*"))

    def one_graph(n: str) -> list[DataFrame]:
        beside.light(n)
        with ThreadPoolExecutor(4) as methods:
            return list(methods.map(lambda a: one(n, a), algos or OWN))

    with ThreadPoolExecutor(3) as pool:
        return reduce(DataFrame.unionAll, [row for rows in pool.map(one_graph, names) for row in rows])


def similarity(spark: SparkSession, folder: str, name: str, algos: list[str]) -> DataFrame:
    """(first, second, edge_rand, pair_rand, adjusted_rand, nmi) between the partitions of each two methods."""
    s, parts = suite(spark, folder), []
    for a in algos:
        s.run(a, name)
    for i, a in enumerate(algos):
        for b in algos[i + 1 :]:
            x, y = s.found[a, name], s.found[b, name]
            parts.append(agreement.edge_rand(s.graph(name), x, y).select("edge_rand").join(agreement.pair_rand(x, y)).select(F.lit(a).alias("first"), F.lit(b).alias("second"), "*"))
    return reduce(DataFrame.unionAll, parts)


def community_graph_of(spark: SparkSession, folder: str, name: str, algo: str) -> DataFrame:
    """Edges of a method's community graph with the sizes of both ends."""
    s = suite(spark, folder)
    s.run(algo, name)
    small, sizes = community_graph(s.light(name), s.found[algo, name])
    a, b = sizes.toDF("u", "size_u"), sizes.toDF("v", "size_v")
    return small.edges.join(a, "u").join(b, "v").select("u", "v", "w", "size_u", "size_v")


def lean_against_dense(spark: SparkSession, g: Graph, max_rounds: int = 2) -> DataFrame:
    """(variant, seconds, ratio, same): the memory-lean move phase and the cached weights against the broadcast one. The graph is
    written and cut into parts once, before the seconds count; the lean variant works on its edges."""
    scratch, rows, marks = Scratch(spark, "lean"), [], []
    g = Graph(*(t if hasattr(t, "_scratch_path") else scratch.write(t) for t in (g.edges, g.nodes)))
    size = propagation.size_of(g)
    if parts.takes(size.low, size.weight, (1, 1)):
        g.parts = parts.cut(g.edges, g.nodes, size.edges, size.weight, scratch)
    for name, k in {"dense": {"state": "broadcast"}, "lean": {"state": "shuffle"}, "cached weights": {"state": "broadcast", "weights": "delta"}, "one task": {"state": "task"}}.items():
        began = time.time()
        found, _ = moves.local_move(g, slots=2, max_rounds=max_rounds, **k)
        marks.append(found.agg(F.sum(F.xxhash64("id", "comm").cast("decimal(38,0)"))).first()[0])
        rows.append((name, time.time() - began))
    return spark.createDataFrame([(n, round(t, 3), round(t / rows[0][1], 3), marks[i] == marks[0]) for i, (n, t) in enumerate(rows)], "variant string, seconds double, ratio double, same boolean")


def gamma_sweep(spark: SparkSession, graphs: dict[str, Graph]) -> DataFrame:
    """(graph, gamma, communities, modularity at gamma 1): resolution from one community to singletons."""
    rows, scratch = [], Scratch(spark, "gamma")
    for name, g in graphs.items():
        g = Graph(scratch.write(g.edges.select("u", "v", "w")), scratch.write(g.nodes))
        for gamma in ((0, 1), (1, 4), (1, 2), (1, 1), (2, 1), (4, 1), (2 * g.total_weight(), 1)):
            q = quality.modularity(g, multilevel.multilevel(g, gamma=gamma)).first()
            rows.append((name, gamma[0] / gamma[1], q["communities"], q["modularity"]))
    return spark.createDataFrame(rows, "graph string, gamma double, communities long, modularity double")


#: Options of label propagation, one changed at a time.
ABLATIONS: dict[str, dict] = {
    "default": {}, "theta 0": {"theta": 0}, "theta 1e-3": {"theta_frac": 1e-3}, "theta 1e-2": {"theta_frac": 1e-2}, "all nodes active": {"frontier": False}, "fixed order": {"rotate": False},
    "random order": {"schedule": "random"}, "synchronous": {"schedule": "sync"}, "ties min": {"ties": "min"}, "ties hash": {"ties": "hash"}, "unweighted": {"weighted": False}, "majority stop": {"stop": "majority", "theta": 0},
}
MOVE_ABLATIONS: dict[str, dict] = {
    "default": {}, "no singleton guard": {"guards": {"slots", "best"}}, "no best guard": {"guards": {"slots", "singleton"}}, "no slots": {"guards": {"singleton", "best"}}, "no guards": {"guards": set()}, "independent set": {"schedule": "independent"},
}


def ablations(spark: SparkSession, folder: str, names: list[str]) -> DataFrame:
    """(graph, method, variant, rounds, evaluated, updated, seconds, communities, modularity, settled)."""
    s, rows = suite(spark, folder), []
    for n in names:
        g = s.graph(n)
        for method, variants in (("LP", ABLATIONS), ("move", MOVE_ABLATIONS)):
            for variant, k in variants.items():
                log, began = RunLog(), time.time()
                found = propagation.propagate_labels(g, log=log, max_rounds=40, **k) if method == "LP" else moves.local_move(g, log=log, **k)[0]
                found = s.scratch.write(found)
                seconds, q = time.time() - began, quality.modularity(g, found).first()
                rows.append((n, method, variant, max((r["round"] for r in log.rows), default=0), sum(r["active"] for r in log.rows), sum(r["updated"] for r in log.rows), round(seconds, 3), q["communities"], q["modularity"], log.settled))
    return spark.createDataFrame(rows, "graph string, method string, variant string, rounds int, evaluated long, updated long, seconds double, communities long, modularity double, settled boolean")


def contraction_control(g: Graph, assignment: DataFrame) -> DataFrame:
    """Contraction in one task, to compare the partitioned one with."""
    a, b = assignment.select(F.col("id").alias("u"), F.col("comm").alias("cu")), assignment.select(F.col("id").alias("v"), F.col("comm").alias("cv"))
    ends = g.edges.coalesce(1).join(F.broadcast(a), "u").join(F.broadcast(b), "v")
    return ends.groupBy(F.least("cu", "cv").alias("u"), F.greatest("cu", "cv").alias("v")).agg(F.sum("w").alias("w"))


def stage_costs(spark: SparkSession, work: Callable[[], object]) -> dict[str, float]:
    """Jobs, shuffled and spilled MB, and the highest memory of one task while `work` runs, from the status store."""
    store = spark._jsc.sc().statusStore()
    gateway = spark.sparkContext._gateway
    none = gateway.jvm.java.util.ArrayList()
    stages = lambda: _rows(store.stageList(none, False, False, gateway.new_array(gateway.jvm.double, 0), none))
    known = {s.stageId() for s in stages()}
    jobs = store.jobsList(None).size()
    began = time.time()
    work()
    fresh = [s for s in stages() if s.stageId() not in known]
    return {
        "seconds": time.time() - began, "jobs": store.jobsList(None).size() - jobs, "shuffle_mb": sum(s.shuffleWriteBytes() for s in fresh) / 1e6, "spill_mb": sum(s.diskBytesSpilled() for s in fresh) / 1e6,
        "task_memory_mb": max((s.peakExecutionMemory() for s in fresh), default=0) / 1e6,
    }


def _rows(found) -> list:
    return [found.apply(i) for i in range(found.size())]


def costs(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """(variant, seconds, jobs, shuffle_mb, spill_mb, task_memory_mb) of two rounds in each physical plan."""
    g, rows = suite(spark, folder).graph(name), []
    for method in ("LP", "move"):
        for state in ("task", "broadcast", "shuffle"):
            work = (lambda st=state: propagation.propagate_labels(g, state=st, max_rounds=2, theta=-1)) if method == "LP" else (lambda st=state: moves.local_move(g, state=st, slots=2, max_rounds=2))
            c = stage_costs(spark, work)
            rows.append((method, state, round(c["seconds"], 3), int(c["jobs"]), round(c["shuffle_mb"], 3), round(c["spill_mb"], 3), round(c["task_memory_mb"], 3)))
    return spark.createDataFrame(rows, "method string, state string, seconds double, jobs int, shuffle_mb double, spill_mb double, task_memory_mb double")


def main(argv: list[str]) -> None:
    """Scaling in fresh sessions: one line of figures for each number of cores."""
    folder = argv[2] if len(argv) > 2 else "/root/testdata/sf0.1"
    for cores in (1, 2, 4, 8):
        spark = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", cores).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").getOrCreate()
        spark.sparkContext.setLogLevel("ERROR")
        g = Suite(spark, folder).graph("basket")
        m = g.edges.count()
        for method in ("LP", "move"):
            began = time.time()
            if method == "LP":
                propagation.propagate_labels(g, state="broadcast", max_rounds=3, theta=-1).count()
            else:
                moves.local_move(g, state="broadcast", max_rounds=1)[0].count()
            seconds = time.time() - began
            print(f"{method} cores {cores} seconds {seconds:.2f} edges/s {m / seconds:.0f}", flush=True)
        spark.stop()


if __name__ == "__main__":
    main(sys.argv)
