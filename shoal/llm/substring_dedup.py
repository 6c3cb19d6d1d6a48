"""Repeated passages: words covered by an n-word window that also starts in a document of smaller id.

Pass 1 counts all windows in count-min sketches (`shoal.llm.sketch`). Pass 2 reads the texts again and
keeps only windows whose cell counts two or more. Inside one task the windows are grouped first: of
equal windows, those of the task's smallest document go on to the exact grouping, the others are known
to be removed already; so a window held by a third of all documents sends at most one document's rows
per task. The exact grouping is by a fingerprint of the window's words (two independent 64-bit
hashes, 96 bits kept). The sketch only spares work: without it the same rows would result.

Defined results: null texts have no words; documents with fewer words than a window, or a null id, are
never changed and never cause a removal; rows that repeat an id are judged one by one and never remove
from each other; all windows are judged on the input, not on what is left of it.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shoal.llm.sketch import pack, pack_rising, repeated_items, shape, unpack, unpack_rising
from shoal.llm.storage import arrow_stage, input_bytes, tidy
from shoal.llm.words import PLAIN, as_strings, find_words, hash_windows, hash_words, mix, slices

#: Candidate windows that a task groups at once.
BLOCK = 4_000_000


def _spans(at: np.ndarray, width: int, n: int) -> np.ndarray:
    """Which of n words are covered by windows that start at `at`."""
    step = np.zeros(n + 1, np.int32)
    np.add.at(step, at, 1)
    np.add.at(step, np.minimum(at + width, n), -1)
    return np.cumsum(step[:n]) > 0


def repeated_windows(docs: DataFrame, width: int = 13, key: str = "doc_id", text: str = "text") -> tuple[DataFrame, Column]:
    """Windows to remove as rows (__id, __tag, __at: starts as bytes), and the tag's expression."""
    found = repeated_items(docs, [F.col(text)], lambda b: _hashes(b.column(0), width))
    # rows that share an id are told apart by their texts; where ids are unique that costs nothing
    alike = not docs.groupBy(F.col(key)).count().where("count > 1").isEmpty()
    tag = F.xxhash64(F.col(text)) if alike else F.lit(0).cast("long")
    bits = shape(input_bytes(docs))[0]
    columns = [F.col(key).cast("long").alias("__id"), F.col(text).alias("__text"), tag.alias("__tag")]

    def windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        n = 0
        for b in batches:
            column, ids, tags = as_strings(b.column(1)), b.column(0), b.column(2).to_numpy()
            known = ids.is_valid().to_numpy(zero_copy_only=False)
            ids = ids.fill_null(0).to_numpy()
            for low, high in slices(column):
                words = find_words(column.slice(low, high - low), PLAIN)
                at, first = hash_windows(words, hash_words(words), width)
                keep = np.flatnonzero(found(first) & known[words.text[at] + low])
                second = hash_windows(words, hash_words(words, 1), width)[1][keep]
                at, first = at[keep], first[keep]
                row = words.text[at]
                held.append((first, (second >> np.uint64(32)).astype(np.uint32), ids[row + low], tags[row + low], (at - words.first[row]).astype(np.uint32)))
                n += len(keep)
                if n >= BLOCK:
                    yield from send(held)
                    held, n = [], 0
        yield from send(held)

    def send(held: list[tuple[np.ndarray, ...]]) -> Iterator[pa.RecordBatch]:
        """Windows of the block's smallest document go on, by ranges of their hash; the others are settled here."""
        if not held:
            return
        (first, second, ids, tags, at), own = _ranked(held)
        yield from _settled(ids[~own], tags[~own], at[~own], bits)
        first, second, ids, tags, at = (x[own] for x in (first, second, ids, tags, at))
        bucket = (first >> np.uint64(64 - bits)).astype(np.int32)
        edge = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1])) if len(bucket) else np.zeros(0, np.int64)
        for low in range(0, len(edge), 256):
            stretch = [slice(a, e) for a, e in zip(edge[low : low + 256], np.append(edge, len(bucket))[low + 1 : low + 257], strict=True)]
            yield pa.RecordBatch.from_arrays([
                pa.array(bucket[edge[low : low + 256]]), pa.array([pack_rising(first[x]) for x in stretch], pa.binary()), pa.array([pack(second[x]) for x in stretch], pa.binary()),
                pa.array([pack(ids[x]) for x in stretch], pa.binary()), pa.array([pack(tags[x]) for x in stretch], pa.binary()), pa.array([pack(at[x]) for x in stretch], pa.binary()),
                pa.nulls(len(stretch), pa.int64()), pa.nulls(len(stretch), pa.int64()),
            ], NAMES)

    def group(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Exact grouping of one range of hashes at a time."""
        bucket, held = None, []

        def done() -> Iterator[pa.RecordBatch]:
            if held:
                (_, _, ids, tags, at), own = _ranked(held)
                yield from _settled(ids[~own], tags[~own], at[~own], None)

        for b in batches:
            ready = b.filter(b.column(6).is_valid())
            if len(ready):
                yield pa.RecordBatch.from_arrays([ready.column(6), ready.column(7), ready.column(5)], ["__id", "__tag", "__at"])
            b = b.filter(b.column(6).is_null())
            for k, *blobs in zip(*(b.column(i).to_pylist() for i in range(6)), strict=True):
                if k != bucket:
                    yield from done()
                    bucket, held = k, []
                held.append((unpack_rising(blobs[0], np.uint64), unpack(blobs[1], np.uint32), unpack(blobs[2], np.int64), unpack(blobs[3], np.int64), unpack(blobs[4], np.uint32)))
        yield from done()

    NAMES = ["__range", "__first", "__second", "__ids", "__tags", "__at", "__id", "__tag"]
    rows = arrow_stage(docs, columns, windows, "__range int, __first binary, __second binary, __ids binary, __tags binary, __at binary, __id long, __tag long")
    settled = rows.repartition(F.col("__range")).sortWithinPartitions("__range").mapInArrow(tidy(group), "__id long, __tag long, __at binary")
    return settled, tag


def _ranked(held: list[tuple[np.ndarray, ...]]) -> tuple[tuple[np.ndarray, ...], np.ndarray]:
    """Windows in the order of their fingerprints, and which belong to the smallest id of their fingerprint."""
    first, second, ids, tags, at = (np.concatenate(x) for x in zip(*held, strict=True))
    order = np.lexsort((ids, second, first))
    first, second, ids = first[order], second[order], ids[order]
    fresh = np.ones(len(first), bool)
    fresh[1:] = (first[1:] != first[:-1]) | (second[1:] != second[:-1])
    owner = ids[fresh][np.cumsum(fresh) - 1] if len(ids) else ids
    return (first, second, ids, tags[order], at[order]), ids == owner


def _settled(ids: np.ndarray, tags: np.ndarray, at: np.ndarray, bits: int | None) -> Iterator[pa.RecordBatch]:
    """One row a document with the starts of its windows to remove; with `bits`, as rows of the first stage."""
    order = np.lexsort((tags, ids))
    ids, tags, at = ids[order], tags[order], at[order]
    place = np.append(np.flatnonzero(np.append(True, (ids[1:] != ids[:-1]) | (tags[1:] != tags[:-1]))) if len(ids) else [], len(ids)).astype(np.int32)
    for low in range(0, len(place) - 1, 50_000):
        high = min(low + 50_000, len(place) - 1)
        head = place[low:high]
        blobs = pa.BinaryArray.from_buffers(pa.binary(), high - low, [None, pa.py_buffer((place[low : high + 1] - place[low]) * np.int32(4)), pa.py_buffer(at[place[low] : place[high]].astype("<i4").tobytes())])
        own = [pa.array(ids[head]), pa.array(tags[head])]
        if bits is None:
            yield pa.RecordBatch.from_arrays([*own, blobs], ["__id", "__tag", "__at"])
        else:
            spread = (mix(ids[head].view(np.uint64)) >> np.uint64(64 - bits)).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(spread), *(pa.nulls(high - low, pa.binary()) for _ in range(4)), blobs, *own], ["__range", "__first", "__second", "__ids", "__tags", "__at", "__id", "__tag"])


def _hashes(column: pa.Array, width: int) -> Iterator[np.ndarray]:
    column = as_strings(column)
    for low, high in slices(column):
        words = find_words(column.slice(low, high - low), PLAIN)
        yield hash_windows(words, hash_words(words), width)[1]


def _with_removals(docs: DataFrame, width: int, key: str, text: str, carry: list[str]) -> DataFrame:
    settled, tag = repeated_windows(docs, width, key, text)
    gone = settled.groupBy("__id", "__tag").agg(F.collect_list("__at").alias("__starts"))
    gone = gone.select(F.col("__id").alias("__gid"), F.col("__tag").alias("__gtag"), "__starts")
    rows = docs.select(*carry, F.col(key).cast("long").alias("__id"), F.col(text).alias("__text"), tag.alias("__tag"))
    return rows.join(gone, (F.col("__id") == F.col("__gid")) & (F.col("__tag") == F.col("__gtag")), "left").drop("__gid", "__gtag")


def _cut(text: str | None, starts: list[bytes] | None, width: int) -> tuple[int, list[bytes]]:
    words = text.encode().split() if text else []
    if not starts:
        return len(words), words
    gone = _spans(np.unique(np.frombuffer(b"".join(starts), "<i4")), width, len(words))
    return len(words), [words[i] for i in np.flatnonzero(~gone).tolist()]


def removal_digests(docs: DataFrame, width: int = 13, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per document: key, n_words, n_removed, kept_sha256 (kept words joined by single blanks)."""
    kind = docs.schema[key].dataType.simpleString()

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            total, left, sha = [], [], []
            for t, starts in zip(b.column(1), b.column(2), strict=True):
                n, kept = _cut(t.as_py(), starts.as_py(), width)
                total.append(n)
                left.append(n - len(kept))
                sha.append(hashlib.sha256(b" ".join(kept)).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(total, pa.int64()), pa.array(left, pa.int64()), pa.array(sha, pa.string())], [key, "n_words", "n_removed", "kept_sha256"])

    rows = _with_removals(docs.select(key, text), width, key, text, [key])
    return arrow_stage(rows, [key, "__text", "__starts"], work, f"{key} {kind}, n_words long, n_removed long, kept_sha256 string")


def remove_repeats(docs: DataFrame, width: int = 13, key: str = "doc_id", text: str = "text") -> DataFrame:
    """All columns of `docs`; texts that lose words hold their kept words joined by single blanks, others stay as they are."""
    others = [c for c in docs.columns if c != text]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [t.as_py() if starts.as_py() is None else b" ".join(_cut(t.as_py(), starts.as_py(), width)[1]).decode() for t, starts in zip(b.column("__text"), b.column("__starts"), strict=True)]
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in others), pa.array(texts, pa.string())], [*others, text])

    rows = _with_removals(docs, width, key, text, others)
    schema = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in [*others, text])
    return arrow_stage(rows, [*others, "__text", "__starts"], work, schema).select(*docs.columns)
