"""Cross-entropy difference: each document's loss under a target and under a background bigram model.

Both models count real words and real word pairs (as 62-bit fingerprints) and share one vocabulary, all
words of the corpus, so their losses can be subtracted token by token. All documents are counted: those
that the labels call good train the target, the others the background. What is counted grows with the input.

Documents are read twice, both times in the same chunks of some tokens. In the first pass a chunk's
distinct items (pairs, words, words as the one before) go with their counts, packed, to the ranges of the
fingerprints; each range adds up all chunks and answers every chunk with the sums of its own items, in its
own order, so they travel back without fingerprints. A frequent item is one entry a chunk, so no key
gathers in one task. In the second pass the chunk's tokens, packed as places in its list of words, meet
the sums and are scored.

The score is the mean over tokens of target loss minus background loss, in nats, rounded to nine
digits; low scores are more like the target. Held-out scoring takes each document's own counts from the
sums first, so no document is recognised by the model that it trained. Interpolation weighs a pair's count against `PRIOR` times
the word's smoothed share, the same for both models.

Defined results: null and empty texts have no tokens, losses and score null; a document with several
labels counts as good if any says so; unlabelled ones are background; empty corpora give uniform models.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shoal.core.storage import Scratch
from shoal.llm.sketch import pack, pack_rising, unpack, unpack_rising
from shoal.llm.storage import arrow_stage, input_bytes
from shoal.llm.words import PLAIN, as_strings, find_words, hash_words, mix, slices

PRIOR = 4.0
#: Tokens of a chunk (or one longer slice of texts).
CHUNK = 800_000
#: Keys of the target's documents that are broadcast (64 MB); more of them are joined.
MOST_KEYS = 8_000_000
#: The two low bits of a fingerprint: pair, word, word as the one before.
_PAIR, _WORD, _BEFORE = np.uint64(0), np.uint64(1), np.uint64(2)
_START, _SPREAD, _KIND = np.uint64(0), np.uint64(0x9E3779B97F4A7C15), np.uint64(3)


class Items:
    """The distinct items of a chunk, by rising fingerprint, and each token's places among them."""

    def __init__(self, words: np.ndarray, own: np.ndarray, counts: np.ndarray) -> None:
        """`words`: hashes of the chunk's distinct words; `own`: each token's place there; `counts`: tokens of each text."""
        n = len(words)
        before = np.empty(len(own), np.int64)
        before[1:] = own[:-1]
        before[(np.cumsum(counts) - counts)[counts > 0]] = n  # a text starts after _START
        codes, pair = np.unique(before * (n + 1) + own, return_inverse=True)
        named = np.append(words, _START)
        kinds = [
            mix(mix(named[codes // (n + 1)]) * _SPREAD + named[codes % (n + 1)]) & ~_KIND | _PAIR,
            mix(words ^ _SPREAD) & ~_KIND | _WORD,
            mix(named) & ~_KIND | _BEFORE,
        ]
        prints = np.concatenate(kinds)
        order = np.argsort(prints, kind="stable")
        self.prints = prints[order]
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        self.pair, self.own, self.before = place[pair], place[len(codes) + own], place[len(codes) + n + before]

    def count(self, use: np.ndarray) -> np.ndarray:
        """How often each item occurs in the tokens of `use`."""
        return sum(np.bincount(at[use], minlength=len(self.prints)) for at in (self.pair, self.own, self.before)).astype(np.int64)


def _runs(batches: Iterator[pa.RecordBatch], column: int) -> Iterator[tuple[int, list[tuple]]]:
    """Rows that follow each other with the same number in a column."""
    at, held = None, []
    for b in batches:
        for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
            if row[column] != at:
                if held:
                    yield at, held
                at, held = row[column], []
            held.append(row)
    if held:
        yield at, held


def _keys_out(keys: pa.Array) -> bytes:
    sink = pa.BufferOutputStream()
    batch = pa.RecordBatch.from_arrays([keys], ["key"])
    with pa.ipc.new_stream(sink, batch.schema) as out:
        out.write_batch(batch)
    return sink.getvalue().to_pybytes()


_CHUNKS = "chunk long, part int, head binary, body binary, more binary"
_NAMES = ["chunk", "part", "head", "body", "more"]
#: The row of a chunk that holds its texts has this part, those with sums have their range.
_TEXTS = -1


@dataclass
class Chunk:
    """Some documents of one task: keys, token counts and label of each, and the tokens."""

    name: int
    keys: pa.Array
    counts: np.ndarray
    good: np.ndarray
    words: np.ndarray  # hashes of the distinct words
    own: np.ndarray  # each token's place among them


def _chunks(batches: Iterator[pa.RecordBatch], held) -> Iterator[Chunk]:
    """Columns are key, text, label key and the number of the input partition. Both passes read the same rows in the same
    order, so they form the same chunks."""
    parts: list[tuple[pa.Array, np.ndarray, np.ndarray, np.ndarray]] = []
    n, number, partition = 0, 0, 0

    def whole() -> Chunk:
        words, own = np.unique(np.concatenate([p[2] for p in parts]), return_inverse=True)
        return Chunk((partition << 32) + number, pa.concat_arrays([p[0] for p in parts]), np.concatenate([p[1] for p in parts]), np.concatenate([p[3] for p in parts]), words, own)

    for b in batches:
        column, good = as_strings(b.column(1)), b.column(2).is_valid().to_numpy(zero_copy_only=False)
        if held is not None:
            good &= np.isin(b.column(2).fill_null(0).to_numpy(), held.value)
        for low, high in slices(column):
            partition = b.column(3)[low].as_py()
            words = find_words(column.slice(low, high - low), PLAIN, lower=True)
            parts.append((b.column(0).slice(low, high - low), words.counts, hash_words(words), good[low:high]))
            n += len(words)
            if n >= CHUNK:
                yield whole()
                parts, n, number = [], 0, number + 1
    if parts:
        yield whole()


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int32()), *(pa.array([r[k] for r in rows], pa.binary()) for k in (2, 3, 4))], _NAMES)


def _item_rows(range_bits: int, held) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Per chunk a row for each range with items there: fingerprints, target counts, background counts."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for chunk in _chunks(batches, held):
            items = Items(chunk.words, chunk.own, chunk.counts)
            target = np.repeat(chunk.good, chunk.counts)
            sums = [items.count(target), items.count(~target)]
            edges = np.append(np.searchsorted(items.prints, np.arange(2**range_bits, dtype=np.uint64) << np.uint64(64 - range_bits)), len(items.prints))
            rows = []
            for r in np.flatnonzero(np.diff(edges) > 0).tolist():
                use = slice(edges[r], edges[r + 1])
                rows.append((chunk.name, r, pack_rising(items.prints[use]), pack(sums[0][use]), pack(sums[1][use])))
            yield _batch(rows)

    return work


def _token_rows(held) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Per chunk its texts: keys with token counts and labels, word hashes, tokens."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for chunk in _chunks(batches, held):
            keys = _keys_out(chunk.keys)
            head = len(keys).to_bytes(8, "little") + keys + pack((chunk.counts.astype(np.uint64) << np.uint64(1)) | chunk.good)
            yield _batch([(chunk.name, _TEXTS, head, pack(chunk.words), pack(chunk.own.astype(np.uint32)))])

    return work


def _add_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For each range and chunk the sums of its items over all chunks; the first row of a range also has the range's
    number of words and of their occurrences on both sides."""
    for part, rows in _runs(batches, 1):
        prints = [unpack_rising(r[2], np.uint64) for r in rows]
        whole, place = np.unique(np.concatenate(prints), return_inverse=True)
        sums = []
        for k in (3, 4):
            total = np.zeros(len(whole), np.int64)
            np.add.at(total, place, np.concatenate([unpack(r[k], np.int64) for r in rows]))
            sums.append(total)
        word = (whole & _KIND) == _WORD
        figures = [int(word.sum()), *(int(t[word].sum()) for t in sums)]
        end = np.cumsum([len(p) for p in prints])
        for i, (row, p) in enumerate(zip(rows, prints, strict=True)):
            own = place[end[i] - len(p) : end[i]]
            yield pa.RecordBatch.from_arrays([
                pa.array([row[0]], pa.int64()), pa.array([part], pa.int32()), pa.array([None], pa.binary()), pa.array([pack(sums[0][own])], pa.binary()), pa.array([pack(sums[1][own])], pa.binary()),
                *(pa.array([f if i == 0 else 0], pa.int64()) for f in figures),
            ], ["chunk", "part", "head", "body", "more", "words", "target", "background"])


def _others(places: np.ndarray, doc: np.ndarray, sums: np.ndarray, mine: np.ndarray) -> np.ndarray:
    """The sums of the tokens' items, less what a token's own document adds to them where it is on that side."""
    codes, at, times = np.unique(doc * np.int64(len(sums)) + places, return_inverse=True, return_counts=True)
    return sums[places] - np.where(mine, times[at], 0)


def _settled_order(rows: DataFrame, scratch: Scratch) -> DataFrame:
    """Rows that both passes read alike: without a shuffle the input's files give their order, otherwise they are written."""
    shuffled = "Exchange" in rows._jdf.queryExecution().executedPlan().toString()
    return scratch.write(rows) if shuffled else rows


def score_documents(docs: DataFrame, good: DataFrame, key: str = "doc_id", text: str = "text", held_out: bool = False) -> DataFrame:
    """One row per document: key, n_tokens, target_loss, background_loss, score.

    With `held_out`, each document is scored by models without its own counts, so that a model does not
    recognise what it was trained on."""
    scratch = Scratch(docs.sparkSession, "losses")
    kind = docs.schema[key].dataType.simpleString()
    keys = good.select(F.col(key).cast("long").alias("__good")).where("__good IS NOT NULL").distinct()
    few = keys.limit(MOST_KEYS + 1).count() <= MOST_KEYS
    marked = docs.select(F.col(key).alias("__id"), F.col(text).alias("__text"), F.col(key).cast("long").alias("__key"))
    held = docs.sparkSession.sparkContext.broadcast(np.sort(keys.toArrow().column(0).to_numpy())) if few else None
    rows = marked if few else marked.join(keys, F.col("__key") == F.col("__good"), "left").select("__id", "__text", "__good")
    rows = _settled_order(rows, scratch).withColumn("__partition", F.spark_partition_id())
    range_bits = int(np.clip(np.ceil(np.log2(max(input_bytes(docs), 1) / 2**24)), 7, 14))
    items = arrow_stage(rows, rows.columns, _item_rows(range_bits, held), _CHUNKS)
    dealt = items.repartition(F.col("part")).sortWithinPartitions("part")
    sums = scratch.write(dealt.mapInArrow(_add_up, f"{_CHUNKS}, words long, target long, background long"))
    words, *tokens = (x or 0 for x in sums.agg(F.sum("words"), F.sum("target"), F.sum("background")).first())

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, (texts, *ranges) in _runs(batches, 0):
            cut = 8 + int.from_bytes(texts[2][:8], "little")
            ids = pa.ipc.open_stream(texts[2][8:cut]).read_all().column(0).combine_chunks()
            flags = unpack(texts[2][cut:], np.uint64)
            n, is_good = (flags >> np.uint64(1)).astype(np.int64), (flags & np.uint64(1)) > 0
            items = Items(unpack(texts[3], np.uint64), unpack(texts[4], np.uint32).astype(np.int64), n)
            doc = np.repeat(np.arange(len(n)), n)
            losses = []
            for k, total, side in zip((3, 4), tokens, (is_good, ~is_good), strict=True):
                sums = np.concatenate([unpack(r[k], np.int64) for r in ranges]) if ranges else np.zeros(0, np.int64)
                if len(sums) != len(items.prints) and len(doc):
                    raise ValueError("the input changed between the two passes")
                if held_out:
                    mine = side[doc]
                    own, pair, before = (_others(at, doc, sums, mine) for at in (items.own, items.pair, items.before))
                    total = total - np.where(side, n, 0)[doc]
                else:
                    own, pair, before = sums[items.own], sums[items.pair], sums[items.before]
                share = (own + 0.5) / (total + 0.5 * words)
                losses.append(np.bincount(doc, weights=-np.log((pair + PRIOR * share) / (before + PRIOR)), minlength=len(n)))
            empty = n == 0
            most = np.maximum(n, 1)
            results = (np.round(x / most, 9) for x in (*losses, losses[0] - losses[1]))
            yield pa.RecordBatch.from_arrays([ids, pa.array(n, pa.int64()), *(pa.array(x, pa.float64(), mask=empty) for x in results)], [key, "n_tokens", "target_loss", "background_loss", "score"])

    met = arrow_stage(rows, rows.columns, _token_rows(held), _CHUNKS).unionByName(sums.select(*_NAMES)).repartition(F.col("chunk")).sortWithinPartitions("chunk", "part")
    return met.mapInArrow(score, f"{key} {kind}, n_tokens long, target_loss double, background_loss double, score double")
