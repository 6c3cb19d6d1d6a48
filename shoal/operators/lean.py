"""Moves on parts of whole nodes without a state that all tasks hold: parts send labels to the parts beside them.

Nodes lie with the arcs of their part; volumes of communities are added up by community and sent back to the parts that
asked. What one part sends to another (its nodes with an arc into it, by rising place) needs no names, as arcs lie in both
directions. Results equal those of the broadcast state.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shoal.core.storage import Scratch
from shoal.operators import onetask
from shoal.operators.parts import Part, PartGraph, _best_moves, _fresh, _numbers, _slices, parts_of

_STATE = "part int, id binary, comm binary, vol binary, moved long, chosen long"


def _longs(column: pa.Array, row: int) -> np.ndarray:
    return _numbers(column, row, np.int64)


def _told(column: pa.Array, row: int, name: str, kind: type = np.int64) -> np.ndarray:
    """One field of all messages of a row, one after the other."""
    return np.concatenate([np.zeros(0, kind), *(np.frombuffer(m[name], kind) for m in column[row].as_py() or ())])


def _arcs(batch: pa.RecordBatch, row: int, number: int) -> Part:
    """The arcs of a row; a part without any has no row in their table."""
    if not batch.column("start")[row].is_valid:
        return Part(np.arange(number), np.zeros(number + 1, np.int32), np.zeros(0, np.int32), np.zeros(0, np.int64))
    return next(parts_of(batch.slice(row, 1), number, 1))._replace(place=np.arange(number))


def move(held: PartGraph, scratch: Scratch, *, gamma: tuple[int, int], slots: int, guards: list[str], max_rounds: int, min_gain: float, seed: int, level: int = 0, phase: str = "move") -> tuple[DataFrame, int, list[dict], bool]:
    """(id, comm), number of moves, log rows, and whether the run settled."""
    spark, parts, total, rows = scratch.spark, held.parts, held.total, []
    slots, guard = slots if "slots" in guards else 1, "singleton" in guards

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, part in enumerate(batch.column("part").to_pylist()):
                label, place = np.unique(_longs(batch.column("comm"), row), return_inverse=True)
                vol = np.zeros(len(label), np.int64)
                np.add.at(vol, place, _longs(batch.column("vol"), row))
                order = np.argsort(label % parts, kind="stable")
                owner = (label % parts)[order]
                fresh = _fresh(owner)
                bounds = np.append(fresh, len(owner))
                yield pa.RecordBatch.from_arrays([pa.array(owner[fresh].astype(np.int32)), pa.array(np.full(len(fresh), part, np.int32)), *(_slices(x[order], bounds) for x in (label, vol, np.bincount(place)))], ["owner", "part", "label", "volume", "size"])

    def answers(asked: list[tuple]) -> pa.RecordBatch:
        names, place = np.unique(np.concatenate([a[1] for a in asked]), return_inverse=True)
        volume, size = np.zeros(len(names), np.int64), np.zeros(len(names), np.int64)
        np.add.at(volume, place, np.concatenate([a[2] for a in asked]))
        np.add.at(size, place, np.concatenate([a[3] for a in asked]))
        bounds = np.append(0, np.cumsum([len(a[1]) for a in asked]))
        squares = [str(sum(x * x for x in volume.tolist()))] + ["0"] * (len(asked) - 1)
        return pa.RecordBatch.from_arrays([pa.array([a[0] for a in asked], pa.int32()), *(_slices(x, bounds) for x in (names[place], volume[place], size[place])), pa.array(squares)], ["part", "label", "volume", "size", "squares"])

    def answer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, asked = -1, []
        for batch in batches:
            for row, (owner, part) in enumerate(zip(batch.column("owner").to_pylist(), batch.column("part").to_pylist(), strict=True)):
                if owner != now and asked:
                    yield answers(asked)
                    asked = []
                now = owner
                asked.append((part, *(_longs(batch.column(c), row).copy() for c in ("label", "volume", "size"))))
        if asked:
            yield answers(asked)

    def own(batch: pa.RecordBatch, row: int) -> tuple[np.ndarray, ...]:
        """Community, its volume and size, of each node."""
        comm = _longs(batch.column("comm"), row)
        if "known" not in batch.schema.names:
            return (comm,)
        label, volume, size = (_told(batch.column("known"), row, c) for c in ("label", "volume", "size"))
        order = np.argsort(label)
        at = order[np.searchsorted(label[order], comm)]
        return comm, volume[at], size[at]

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, part in enumerate(batch.column("part").to_pylist()):
                state = own(batch, row)
                node, dst, _ = (arcs := _arcs(batch, row, len(state[0]))).arcs(np.ones(1, bool))
                number = max(1, len(arcs.place))
                key = np.unique(dst.astype(np.int64) % parts * number + node)
                to, node = key // number, key % number
                fresh = _fresh(to)
                bounds = np.append(fresh, len(to))
                told = [_slices(x[node], bounds) for x in state] + [pa.array([b""] * len(fresh), pa.binary())] * (3 - len(state))
                yield pa.RecordBatch.from_arrays([pa.array(to[fresh].astype(np.int32)), pa.array(np.full(len(fresh), part, np.int32)), *told], ["part", "src", "comm", "volume", "size"])

    def heard(batch: pa.RecordBatch, row: int, dst: np.ndarray, fields: tuple[str, ...]) -> tuple[np.ndarray, ...]:
        """Place of each arc's end among the distinct ends, and what those were told to be."""
        ends, place = np.unique(dst, return_inverse=True)
        order = np.lexsort((ends, ends % parts))
        found = []
        for name in fields:
            values = np.empty(len(ends), np.int64)
            values[order] = _told(batch.column("heard"), row, name)
            found.append(values)
        return place, *found

    def inside(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sums = []
            for row in range(batch.num_rows):
                comm = _longs(batch.column("comm"), row)
                node, dst, w = _arcs(batch, row, len(comm)).arcs(np.ones(1, bool))
                place, there = heard(batch, row, dst, ("comm",))
                sums.append(int(w[comm[node] == there[place]].sum(dtype=np.int64)))
            yield pa.RecordBatch.from_arrays([pa.array(sums, pa.int64())], ["inner"])

    def choose(round_no: int, s: int):
        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for row, part in enumerate(batch.column("part").to_pylist()):
                    ids, vol = _longs(batch.column("id"), row), _longs(batch.column("vol"), row)
                    comm, volume, size = own(batch, row)
                    arcs = _arcs(batch, row, len(ids))
                    place, *there = heard(batch, row, arcs.dst, ("comm", "volume", "size"))
                    names, first, code = np.unique(np.concatenate([comm, there[0]]), return_index=True, return_inverse=True)
                    volume, size = (np.concatenate(x)[first] for x in ((volume, there[1]), (size, there[2])))
                    chosen = np.ones(len(ids), bool) if slots == 1 else onetask.slots_of(ids, round_no, slots, seed) == s
                    node, to = _best_moves(arcs._replace(dst=len(ids) + place), code, vol, volume, (size == 1) & guard, total, gamma, chosen)
                    comm = comm.copy()
                    comm[node] = names[to]
                    yield pa.RecordBatch.from_arrays([batch.column("part").slice(row, 1), batch.column("id").slice(row, 1), pa.array([comm.tobytes()], pa.binary()), batch.column("vol").slice(row, 1), pa.array([len(node)]), pa.array([int(chosen.sum())])], _STATE.replace(" int", "").replace(" binary", "").replace(" long", "").split(", "))

        return work

    def gathered(table: DataFrame, name: str) -> DataFrame:
        return table.groupBy("part").agg(F.collect_list(F.struct(*(c for c in table.columns if c not in ("part", "squares")))).alias(name))

    def known(state: DataFrame) -> DataFrame:
        asked = state.mapInArrow(ask, "owner int, part int, label binary, volume binary, size binary")
        return scratch.write(asked.repartition("owner").sortWithinPartitions("owner").mapInArrow(answer, "part int, label binary, volume binary, size binary, squares string"))

    def told(beside: DataFrame) -> DataFrame:
        return beside.join(gathered(beside.mapInArrow(send, "part int, src int, comm binary, volume binary, size binary").sortWithinPartitions("src"), "heard").withColumn("heard", F.array_sort("heard")), "part", "left")

    def quality(state: DataFrame, replies: DataFrame) -> float:
        inner = told(state.join(arcs, "part", "left")).mapInArrow(inside, "inner long").agg(F.sum("inner")).first()[0] // 2 + int(held.loops.sum())
        return onetask.rounded(inner, sum(int(r[0]) for r in replies.select("squares").collect()), 2 * total, gamma)

    begin = [(p, *(x[p::parts].tobytes() for x in (held.ids, held.ids, held.vol)), 0, 0) for p in range(min(parts, len(held.ids)))]
    state = scratch.write(spark.createDataFrame(begin, _STATE))
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    arcs = held.table.select("part", "start", "dst", "w").repartition(tasks, "part").persist()
    moved_total, settled, best = 0, not total, state
    try:
        replies = known(state)
        value = best_value = quality(state, replies) if total else 0.0
        for round_no in range(1, max_rounds + 1 if total else 0):
            moved = 0
            for s in range(slots):
                began = time.time()
                beside = state.join(arcs, "part", "left").join(gathered(replies, "known"), "part", "left")
                state = scratch.write(told(beside).mapInArrow(choose(round_no, s), _STATE))
                count, chosen = state.agg(F.sum("moved"), F.sum("chosen")).first()
                scratch.drop(replies)
                replies = known(state)
                moved += count
                rows.append({"level": level, "phase": phase, "round": round_no, "slot": s, "updated": count, "active": chosen, "seconds": time.time() - began})
            moved_total += moved
            settled = not moved
            if not settled:
                after = quality(state, replies)
                gain, value = after - value, after
                if after > best_value or "best" not in guards:
                    best, best_value = state, after
                settled = gain < min_gain
            if settled:
                break
    finally:
        arcs.unpersist()
    found = best if "best" in guards else state

    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                yield pa.RecordBatch.from_arrays([pa.array(_longs(batch.column(c), row)) for c in ("id", "comm")], ["id", "comm"])

    return found.mapInArrow(listed, "id long, comm long"), moved_total, rows, settled
