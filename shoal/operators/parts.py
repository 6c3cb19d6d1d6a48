"""Graphs whose arcs lie in parts of whole nodes, for the methods of `onetask` where the state of all nodes is broadcast.

A part holds its nodes' arcs as arrays in one row of a written table, so a sub-round reads and adds up arrays instead of
joining rows. Tasks get the state of all nodes and give back the nodes that change; the state stays on the driver, which
a broadcast join would send it through as well. Results equal the joins' row by row.
"""

from __future__ import annotations

import json
import tempfile
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shoal.core.storage import Scratch
from shoal.functions.scalar import PRIME

#: Arcs of a part, about (a part holds whole nodes), and edges that are dealt out to parts at once.
PART_ARCS, DEALT = 1 << 18, 1 << 19
#: Parts of a file: a reader holds them all at once.
FILE_PARTS = 8
_PART = "part int, start binary, dst binary, w binary, vol binary"


class Part(NamedTuple):
    """Places of nodes, where the arcs of each begin, and the other ends' places and weights."""

    place: np.ndarray
    start: np.ndarray
    dst: np.ndarray
    w: np.ndarray

    def arcs(self, use: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(node within the part, dst, w) of the arcs of some of its nodes."""
        degree = np.diff(self.start)
        node = np.repeat(np.arange(len(degree)), degree)
        if use.all():
            return node, self.dst, self.w
        take = np.repeat(use, degree)
        return node[take], self.dst[take], self.w[take]


def _fresh(key: np.ndarray) -> np.ndarray:
    """Where a new value begins."""
    return np.flatnonzero(np.append(True, key[1:] != key[:-1])) if len(key) else np.zeros(0, np.int64)


def _to_labels(part: Part, code: np.ndarray, use: np.ndarray, weighted: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(node, label, weight) by rising node and label."""
    node, dst, w = part.arcs(use)
    w = w.astype(np.int64) if weighted else np.ones(len(dst), np.int64)
    bits, size = len(code).bit_length(), int(w.max(initial=1)).bit_length()
    key = (node << bits) | code[dst]
    if len(part.place).bit_length() + bits + size < 63:
        key = (key << size) | w
        key.sort()
        key, w = key >> size, key & ((1 << size) - 1)
    else:
        order = np.argsort(key, kind="stable")
        key, w = key[order], w[order]
    fresh = _fresh(key)
    key, w = key[fresh], np.add.reduceat(w, fresh) if len(key) else w
    return key >> bits, key & ((1 << bits) - 1), w


def _first(node: np.ndarray, score: np.ndarray) -> np.ndarray:
    """For each node the first of its rows of highest score."""
    lead = _fresh(node)
    if not len(lead):
        return lead
    most = np.repeat(np.maximum.reduceat(score, lead), np.diff(np.append(lead, len(node))))
    top = np.flatnonzero(score == most)
    return top[_fresh(node[top])]


def _winners(part: Part, code: np.ndarray, evaluated: np.ndarray, keep: bool, weighted: bool) -> tuple[np.ndarray, np.ndarray]:
    node, label, w = _to_labels(part, code, evaluated[part.place], weighted)
    mine = code[part.place]
    top = _first(node, 2 * w + (label == mine[node]) if keep else w)
    node, label = node[top], label[top]
    moved = label != mine[node]
    return part.place[node[moved]], label[moved]


def _touched(part: Part, mark: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    node, dst, _ = part.arcs(np.ones(1, bool))
    out = np.zeros(len(part.place), bool)
    out[node[mark[dst]]] = True
    return part.place[out], part.place[:0]


def _inner(part: Part, code: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    node, dst, w = part.arcs(np.ones(1, bool))
    return w[code[part.place][node] == code[dst]].sum(keepdims=True, dtype=np.int64), part.place[:0]


def _inner_of(part: Part, code: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Communities with arcs inside, and their weight, each edge twice."""
    node, dst, w = part.arcs(np.ones(1, bool))
    label = code[part.place][node]
    same = label == code[dst]
    label, w = label[same], w[same]
    order = np.argsort(label, kind="stable")
    fresh = _fresh(label[order])
    return label[order][fresh], np.add.reduceat(w[order], fresh, dtype=np.int64) if len(fresh) else np.zeros(0, np.int64)


def _agreeing(part: Part, first: np.ndarray, second: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    node, dst, _ = part.arcs(np.ones(1, bool))
    node = part.place[node]
    same = (first[node] == first[dst]) == (second[node] == second[dst])
    return same.sum(keepdims=True), np.array([len(same)])


def _beaten(part: Part, ranks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    own = ranks[part.place]
    node, dst, _ = part.arcs(own >= 0)
    a, b, p, q = own[node], ranks[dst], part.place[node], dst
    out = np.zeros(len(part.place), bool)
    out[node[(b >= 0) & ((b > a) | ((b == a) & (q < p)))]] = True
    return part.place[out], part.place[:0]


def _best_moves(part: Part, code: np.ndarray, vol: np.ndarray, volume: np.ndarray, single: np.ndarray, total: int, gamma: tuple[int, int], chosen: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return best_of(part, code, vol, volume, single, total, gamma, *_to_labels(part, code, chosen[part.place]))


def best_of(part: Part, code: np.ndarray, vol: np.ndarray, volume: np.ndarray, single: np.ndarray, total: int, gamma: tuple[int, int], node: np.ndarray, label: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of nodes with a move of positive score, and where each goes, from the weights to communities."""
    p, q = gamma
    mine, vol = code[part.place], vol[part.place]
    inner, own = np.zeros(len(mine), np.int64), label == mine[node]
    inner[node[own]] = w[own]
    node, label, w = node[~own], label[~own], w[~own]
    source, vk = mine[node], vol[node]
    score = 2 * q * total * (w - inner[node]) + p * vk * (volume[source] - vk - volume[label])
    good = (score > 0) & ~(single[source] & single[label] & (label > source))
    node, label = node[good], label[good]
    top = _first(node, score[good])
    return part.place[node[top]], label[top]


@dataclass
class PartGraph:
    """Nodes by rising id with their volumes and loops; `each` runs a function of a part, and of what it is given, on
    all parts and returns what they found."""

    ids: np.ndarray
    vol: np.ndarray
    loops: np.ndarray
    each: Callable[..., tuple[np.ndarray, np.ndarray]]
    table: DataFrame | None = None
    parts: int = 1
    alone: bool = False  # each run is one task over all parts, for many runs at the same time

    @property
    def total(self) -> int:
        return int(self.vol.sum()) // 2

    def beside(self, spark: SparkSession, tasks: int) -> PartGraph:
        """The same parts, read in so many tasks of another session."""
        table = spark.read.schema(self.table.schema).parquet(self.table._scratch_path).coalesce(tasks)
        return PartGraph(self.ids, self.vol, self.loops, _on_spark(table, len(self.ids), self.parts), self.table, self.parts)

    def marked(self, place: np.ndarray) -> np.ndarray:
        out = np.zeros(len(self.ids), bool)
        out[place] = True
        return out

    def inner(self, comm: np.ndarray) -> int:
        """Weight inside communities, loops included."""
        code = np.unique(comm, return_inverse=True)[1].astype(np.int32)
        return int(self.each(_inner, code)[0].sum()) // 2 + int(self.loops.sum())

    def agreeing(self, first: np.ndarray, second: np.ndarray) -> tuple[int, int]:
        """Edges that two partitions both put inside, or both between, communities; and all edges, loops apart."""
        agree, arcs = self.each(_agreeing, *(np.unique(x, return_inverse=True)[1].astype(np.int32) for x in (first, second)))
        return int(agree.sum()) // 2, int(arcs.sum()) // 2

    def labels(self, assignment: DataFrame) -> np.ndarray | None:
        """The community of each node; None unless the assignment names each node once."""
        rows = assignment.select("id", "comm").toArrow()
        comm, order = rows["comm"].to_numpy(), np.argsort(rows["id"].to_numpy())
        return comm[order] if np.array_equal(rows["id"].to_numpy()[order], self.ids) else None

    def communities(self, comm: np.ndarray) -> tuple[np.ndarray, ...]:
        """(names, sizes, volumes, weights inside, loops included) of communities."""
        names, code, size = np.unique(comm, return_inverse=True, return_counts=True)
        vol, inner = np.zeros(len(names), np.int64), np.zeros(len(names), np.int64)
        label, twice = self.each(_inner_of, code.astype(np.int32))
        np.add.at(inner, label, twice)
        inner //= 2
        np.add.at(inner, code, self.loops)
        np.add.at(vol, code, self.vol)
        return names, size, vol, inner

    def contracted(self, comm: np.ndarray) -> DataFrame:
        """(u, v, w): edges between communities and inside them, summed up in each part."""
        names, code = np.unique(comm, return_inverse=True)
        nodes, parts, spark = len(self.ids), self.parts, self.table.sparkSession
        held = spark.sparkContext.broadcast((names, code.astype(np.int32)))  # read when the table is: not destroyed here

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            names, code = held.value
            for batch in batches:
                for part in parts_of(batch, nodes, parts):
                    node, dst, w = part.arcs(np.ones(1, bool))
                    once = part.place[node] < dst
                    a, b, w = code[part.place][node[once]].astype(np.int64), code[dst[once]].astype(np.int64), w[once]
                    key = np.minimum(a, b) * len(names) + np.maximum(a, b)
                    order = np.argsort(key, kind="stable")
                    fresh = _fresh(key[order])
                    key = key[order][fresh]
                    w = np.add.reduceat(w[order], fresh, dtype=np.int64) if len(fresh) else np.zeros(0, np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(names[key // len(names)]), pa.array(names[key % len(names)]), pa.array(w)], ["u", "v", "w"])

        own = np.flatnonzero(self.loops)
        loops = spark.createDataFrame(pa.table({"u": comm[own], "v": comm[own], "w": self.loops[own]}), "u long, v long, w long")
        return self.table.select("part", "start", "dst", "w").mapInArrow(work, "u long, v long, w long").unionAll(loops)

    def touched(self, mark: np.ndarray) -> np.ndarray:
        """Nodes beside a marked one."""
        return self.marked(self.each(_touched, mark)[0])

    def beaten(self, node: np.ndarray, rank: np.ndarray) -> np.ndarray:
        """For each of the nodes, whether one of them beside it has a higher rank (or the same and a smaller id)."""
        ranks = np.full(len(self.ids), -1, np.int64)
        ranks[node] = rank
        return self.marked(self.each(_beaten, ranks)[0])[node]

    def winners(self, comm: np.ndarray, evaluated: np.ndarray, ties: str, weighted: bool, seed: int) -> tuple[np.ndarray, np.ndarray]:
        """Places of evaluated nodes that another label wins, and that label."""
        names, code = np.unique(comm, return_inverse=True)
        if ties == "hash":  # labels in the order in which equal weights prefer them
            order = np.lexsort((names, (names % PRIME + seed) * 48271 % PRIME))
            back = np.empty_like(order)
            back[order] = np.arange(len(order))
            names, code = names[order], back[code]
        node, to = self.each(_winners, code.astype(np.int32), evaluated, ties == "keep_min", weighted)
        return node, names[to]

    def best_moves(self, comm: np.ndarray, vol: np.ndarray, total: int, gamma: tuple[int, int], chosen: np.ndarray, single_guard: bool) -> tuple[np.ndarray, np.ndarray]:
        names, code = np.unique(comm, return_inverse=True)
        volume = np.zeros(len(names), np.int64)
        np.add.at(volume, code, vol)
        single = (np.bincount(code, minlength=len(names)) == 1) & single_guard
        node, to = self.each(_best_moves, code.astype(np.int32), vol, volume, single, total, gamma, chosen)
        return node, names[to]

    def state(self, start: DataFrame | None, active: DataFrame | None) -> tuple[np.ndarray, np.ndarray]:
        """Labels and active nodes at the begin."""
        comm, on = self.ids.copy(), np.full(len(self.ids), active is None)
        if start is not None:
            rows = start.select("id", "comm").toArrow()
            comm[np.searchsorted(self.ids, rows["id"].to_numpy())] = rows["comm"].to_numpy()
        if active is not None:
            on[np.searchsorted(self.ids, active.select("id").toArrow()["id"].to_numpy())] = True
        return comm, on

    def written(self, scratch: Scratch, comm: np.ndarray) -> DataFrame:
        return scratch.write(scratch.spark.createDataFrame(pa.table({"id": self.ids, "comm": comm}), "id long, comm long"))


def takes(low: int, weight: int, gamma: tuple[int, int] = (0, 0)) -> bool:
    """Whether sums and scores of such a graph fit 63 bits, and its ids the hash of slots."""
    return low >= 0 and weight < 1 << 60 and (4 * gamma[0] + 2 * gamma[1]) * weight * weight < 1 << 62


def _numbers(column: pa.Array, row: int, kind: type) -> np.ndarray:
    return np.frombuffer(column[row].as_buffer(), kind)


def parts_of(batch: pa.RecordBatch, nodes: int, parts: int) -> Iterator[Part]:
    for row, part in enumerate(batch.column("part").to_pylist()):
        dst = _numbers(batch.column("dst"), row, np.int32)
        size = len(batch.column("w")[row].as_buffer()) // max(1, len(dst))
        yield Part(np.arange(part, nodes, parts), _numbers(batch.column("start"), row, np.int32), dst, _numbers(batch.column("w"), row, np.dtype(f"i{size}") if len(dst) else np.int64))


def _on_spark(table: DataFrame, nodes: int, parts: int) -> Callable[..., tuple[np.ndarray, np.ndarray]]:
    table = table.select("part", "start", "dst", "w")

    def each(fn: Callable, *args) -> tuple[np.ndarray, np.ndarray]:
        held = table.sparkSession.sparkContext.broadcast(args)

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                found = [fn(part, *held.value) for part in parts_of(batch, nodes, parts)]
                yield pa.RecordBatch.from_arrays([pa.array([np.concatenate(x).astype(np.int64).tobytes()], pa.binary()) for x in zip(*found, strict=True)], ["a", "b"])

        try:
            rows = table.mapInArrow(work, "a binary, b binary").collect()
        finally:
            held.destroy()
        return tuple(np.concatenate([np.zeros(0, np.int64), *(np.frombuffer(r[i], np.int64) for r in rows)]) for i in range(2))

    return each


def _slices(values: np.ndarray, bounds: np.ndarray) -> pa.Array:
    """A binary column of consecutive pieces."""
    return pa.Array.from_buffers(pa.binary(), len(bounds) - 1, [None, pa.py_buffer((bounds * values.itemsize).astype(np.int32)), pa.py_buffer(np.ascontiguousarray(values))])


def cut(edges: DataFrame, nodes: DataFrame, count: int, weight: int, scratch: Scratch) -> PartGraph:
    """The graph of so many edges and this weight in parts: edges are dealt out in pieces, each part is put together once."""
    ids = np.sort(nodes.select("id").toArrow()["id"].to_numpy())
    n, parts = len(ids), max(1, -(-2 * count // PART_ARCS))
    held, kind = scratch.spark.sparkContext.broadcast(ids), np.int32 if weight < 1 << 31 else np.int64

    def pieces(rows: list[list[np.ndarray]]) -> pa.RecordBatch:
        u, v, w = (np.concatenate(x) for x in zip(*rows, strict=True))
        keep = u != v
        a, b, w = np.searchsorted(held.value, u[keep]), np.searchsorted(held.value, v[keep]), w[keep].astype(kind)
        src, dst, w = np.concatenate([a, b]), np.concatenate([b, a]).astype(np.int32), np.concatenate([w, w])
        part = src % parts
        order = np.argsort(part.astype(np.uint16) if parts < 1 << 16 else part, kind="stable")
        part = part[order]
        fresh = _fresh(part)
        bounds = np.append(fresh, len(part))
        return pa.RecordBatch.from_arrays([pa.array(part[fresh].astype(np.int32)), _slices((src // parts).astype(np.int32)[order], bounds), _slices(dst[order], bounds), _slices(w[order], bounds)], ["part", "src", "dst", "w"])

    def dealt(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, size = [], 0
        for batch in batches:
            rows.append([c.to_numpy() for c in batch.columns])
            size += batch.num_rows
            if size >= DEALT:
                yield pieces(rows)
                rows, size = [], 0
        if rows:
            yield pieces(rows)

    def whole(part: int, rows: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
        src, dst, w = (np.concatenate(x) for x in zip(*rows, strict=True))
        number = len(range(part, n, parts))
        order = np.argsort(src.astype(np.uint16) if number <= 1 << 16 else src, kind="stable")
        start = np.append(0, np.cumsum(np.bincount(src, minlength=number)))
        w = w[order].astype(np.int64)
        upto = np.append(0, np.cumsum(w))
        size = next(s for s in (1, 2, 4, 8) if int(w.max(initial=0)) < 1 << (8 * s - 1))
        values = start.astype(np.int32), dst[order], w.astype(f"i{size}"), upto[start[1:]] - upto[start[:-1]]
        return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), *(pa.array([x.tobytes()], pa.binary()) for x in values)], ["part", "start", "dst", "w", "vol"])

    def joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, rows = -1, []
        for batch in batches:
            for row, part in enumerate(batch.column("part").to_pylist()):
                if part != now and rows:
                    yield whole(now, rows)
                    rows = []
                now = part
                rows.append((_numbers(batch.column("src"), row, np.int32), _numbers(batch.column("dst"), row, np.int32), _numbers(batch.column("w"), row, kind)))
        if rows:
            yield whole(now, rows)

    loose = edges.select("u", "v", "w").mapInArrow(dealt, "part int, src binary, dst binary, w binary")
    table = scratch.write(loose.repartition("part").sortWithinPartitions("part").mapInArrow(joined, _PART), FILE_PARTS)
    vol, loops = np.zeros(n, np.int64), np.zeros(n, np.int64)
    for row in table.select("part", "vol").collect():
        vol[row["part"] :: parts] = np.frombuffer(row["vol"], np.int64)
    own = edges.where("u = v").groupBy("u").agg(F.sum("w").alias("w")).toArrow()
    loops[np.searchsorted(ids, own["u"].to_numpy())] = own["w"].to_numpy()
    held.destroy()
    return PartGraph(ids, vol + 2 * loops, loops, _on_spark(table, n, parts), table, parts)


def in_one_task(held: PartGraph, scratch: Scratch, solve: Callable[[PartGraph], tuple]) -> tuple[DataFrame, list]:
    """(id, comm) from solve(graph) -> labels, and the rest of what it returns, run by one task over all parts: their arcs lie in a
    file of the task's own, so the task holds the state and a part at a time."""
    ids, vol, loops, parts = held.ids, held.vol, held.loops, held.parts
    state = scratch.spark.sparkContext.broadcast((ids, vol, loops))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, vol, loops = state.value
        with tempfile.TemporaryFile() as file:
            places = []
            for batch in batches:
                for row, part in enumerate(batch.column("part").to_pylist()):
                    blobs = [batch.column(c)[row].as_buffer() for c in ("start", "dst", "w")]
                    places.append((part, file.tell(), [b.size for b in blobs]))
                    for b in blobs:
                        file.write(b)

            def each(fn: Callable, *args) -> tuple[np.ndarray, np.ndarray]:
                found = [(np.zeros(0, np.int64),) * 2]
                for part, at, sizes in places:
                    file.seek(at)
                    start, dst, w = (file.read(n) for n in sizes)
                    dst = np.frombuffer(dst, np.int32)
                    kind = np.dtype(f"i{len(w) // len(dst)}") if len(dst) else np.int64
                    found.append(fn(Part(np.arange(part, len(ids), parts), np.frombuffer(start, np.int32), dst, np.frombuffer(w, kind)), *args))
                return tuple(np.concatenate(x).astype(np.int64) for x in zip(*found, strict=True))

            comm, *rest = solve(PartGraph(ids, vol, loops, each, None, parts))
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(comm), pa.nulls(len(ids), pa.string())], ["id", "comm", "note"])
        yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64()), pa.array([json.dumps(rest)])], ["id", "comm", "note"])

    table = scratch.write(held.table.select("part", "start", "dst", "w").coalesce(1).mapInArrow(work, "id long, comm long, note string"))
    state.destroy()
    return table.where("note IS NULL").select("id", "comm"), json.loads(table.where("note IS NOT NULL").first()["note"])


class CachedParts(PartGraph):
    """Parts that keep the weights from their nodes to communities beside their arcs, in a table of their own: movers change
    them by signed rows, and moves are chosen from the table."""

    names, code, cached = None, None, None

    @staticmethod
    def of(held: PartGraph, scratch: Scratch) -> CachedParts:
        out = CachedParts(held.ids, held.vol, held.loops, held.each, held.table, held.parts)
        out.scratch = scratch
        return out

    def best_moves(self, comm: np.ndarray, vol: np.ndarray, total: int, gamma: tuple[int, int], chosen: np.ndarray, single_guard: bool) -> tuple[np.ndarray, np.ndarray]:
        names = np.unique(comm) if self.names is None else self.names  # nodes move to communities that were there at the begin
        code = np.searchsorted(names, comm).astype(np.int32)
        volume = np.zeros(len(names), np.int64)
        np.add.at(volume, code, vol)
        single = (np.bincount(code, minlength=len(names)) == 1) & single_guard
        before, nodes, parts = code if self.code is None else self.code, len(self.ids), self.parts
        args = self.scratch.spark.sparkContext.broadcast((before, code, vol, volume, single, total, gamma, chosen))

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            before, code, vol, volume, single, total, gamma, chosen = args.value
            moved = before != code
            for batch in batches:
                for row, part in enumerate(parts_of(batch, nodes, parts)):
                    if "label" in batch.schema.names:
                        node, label, w = _numbers(batch.column("node"), row, np.int32).astype(np.int64), _numbers(batch.column("label"), row, np.int32).astype(np.int64), _numbers(batch.column("weight"), row, np.int64)
                    else:
                        node, label, w = _to_labels(part, before, np.ones(1, bool))
                    if moved.any():
                        src, dst, change = part.arcs(np.ones(1, bool))
                        some = moved[dst]
                        src, dst, change = src[some], dst[some], change[some].astype(np.int64)
                        node, label, w = np.concatenate([node, src, src]), np.concatenate([label, before[dst], code[dst]]), np.concatenate([w, -change, change])
                        bits = len(code).bit_length()
                        key = (node << bits) | label
                        order = np.argsort(key, kind="stable")
                        key, w = key[order], w[order]
                        fresh = _fresh(key)
                        key, w = key[fresh], np.add.reduceat(w, fresh) if len(key) else w
                        key, w = key[w != 0], w[w != 0]
                        node, label = key >> bits, key & ((1 << bits) - 1)
                    use = chosen[part.place][node]
                    found = best_of(part, code, vol, volume, single, total, gamma, node[use], label[use], w[use])
                    values = [x.tobytes() for x in (node.astype(np.int32), label.astype(np.int32), w, *(f.astype(np.int64) for f in found))]
                    yield pa.RecordBatch.from_arrays([*(batch.column(c).slice(row, 1) for c in ("part", "start", "dst", "w")), *(pa.array([x], pa.binary()) for x in values)], ["part", "start", "dst", "w", "node", "label", "weight", "a", "b"])

        table = self.table.select("part", "start", "dst", "w") if self.cached is None else self.cached.drop("a", "b")
        after = self.scratch.write(table.mapInArrow(work, "part int, start binary, dst binary, w binary, node binary, label binary, weight binary, a binary, b binary"), FILE_PARTS)
        self.scratch.drop(self.cached)
        self.names, self.code, self.cached = names, code, after
        rows = after.select("a", "b").collect()
        args.destroy()
        node, to = (np.concatenate([np.zeros(0, np.int64), *(np.frombuffer(r[i], np.int64) for r in rows)]) for i in range(2))
        return node, names[to]
