"""Benchmark passages in training documents, found through an FM-index of each training shard.

A shard is a bounded run of documents of one task. Its words become symbols: words that occur in no
benchmark item share one symbol and runs of them shrink to one, so the text to index is short and loses
nothing a phrase could match. The shard's suffixes are sorted (prefix doubling on the undecided ones),
the last-column transform goes into a wavelet matrix, and all phrases are searched backwards together,
each step being two rank queries. Occurrences are located by walking back to sampled suffix positions.
Hit words are the merged spans of all occurrences.

Phrases are each item's windows of `width` words; an item with fewer words is one window. Items are
collected and broadcast after their total size is checked against `ITEM_BYTES`; a larger benchmark is
searched in blocks of items of that size, one pass over the documents each, and the spans are merged.

Defined results: null and empty texts have no words and no hits; items without words give no window;
items that repeat an id count once; repeated documents are judged one by one.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shoal.core.storage import Scratch
from shoal.llm.storage import tidy
from shoal.llm.words import ALNUM, as_strings, find_words, hash_words, slices

#: Symbols of one shard's index, and bytes of benchmark text that are broadcast at once.
SHARD = 750_000
ITEM_BYTES = 32 << 20
SAMPLE = 8
_OTHER, _FIRST = 1, 2  # 0 ends a document


@dataclass
class Phrases:
    """Distinct windows of the items as rows of symbols (the last words stand at the end of a row)."""

    known: np.ndarray  # rising word fingerprints; symbol = place + _FIRST
    symbols: np.ndarray  # windows x width, filled up with -1 in front
    size: np.ndarray
    items: list[np.ndarray] = field(default_factory=list)  # item numbers of each window
    names: list[str] = field(default_factory=list)

    @staticmethod
    def of(rows: list[tuple[str, str]], width: int) -> Phrases:
        column = as_strings(pa.array([t for _, t in rows], pa.string()))
        words = find_words(column, ALNUM, lower=True)
        h = hash_words(words)
        known = np.unique(h)
        symbol = np.searchsorted(known, h) + _FIRST
        windows: dict[tuple[int, ...], set[int]] = {}
        names = sorted({n for n, _ in rows})
        number = {n: i for i, n in enumerate(names)}
        for i, (a, b) in enumerate(zip(words.first[:-1].tolist(), words.first[1:].tolist(), strict=True)):
            own = symbol[a:b].tolist()
            for k in range(max(1, len(own) - width + 1) if own else 0):
                windows.setdefault(tuple(own[k : k + width]), set()).add(number[rows[i][0]])
        table = np.full((len(windows), width), -1, np.int64)
        for row, w in zip(table, windows, strict=True):
            row[width - len(w) :] = w
        return Phrases(known, table, np.array([len(w) for w in windows], np.int64), [np.array(sorted(v)) for v in windows.values()], names)


def suffix_array(text: np.ndarray) -> np.ndarray:
    """Starts of the suffixes of `text` (small non-negative numbers) in their order; a suffix precedes its extensions."""
    n = len(text)
    bits = max(1, int(text.max() + 1).bit_length())
    depth = max(1, 62 // bits)
    key = np.zeros(n, np.uint64)
    for j in range(depth):
        key <<= np.uint64(bits)
        if j < n:
            key[: n - j] |= (text[j:] + 1).astype(np.uint64)
    order = np.argsort(key, kind="stable")
    rank = np.empty(n, np.int64)
    fresh = np.append(True, key[order][1:] != key[order][:-1])
    head = np.flatnonzero(fresh)
    group = np.repeat(head, np.diff(np.append(head, n)))  # a rank is the first place of its group
    rank[order] = group
    while True:
        size = np.diff(np.append(head, n))
        tied = np.repeat(size > 1, size)
        place = np.flatnonzero(tied)
        if not len(place):
            return order
        who = order[place]
        after = who + depth
        second = np.where(after < n, rank[np.minimum(after, n - 1)] + 1, 0)
        first = group[place]
        inner = np.argsort(first * np.int64(n + 1) + second, kind="stable")  # below 2 ** 62
        who, second, first = who[inner], second[inner], first[inner]
        order[place] = who
        new = np.append(True, (first[1:] != first[:-1]) | (second[1:] != second[:-1]))
        fresh = np.ones(n, bool)
        fresh[place] = new
        head = np.flatnonzero(fresh)
        group = np.repeat(head, np.diff(np.append(head, n)))
        rank[who] = group[place]
        depth *= 2


class Wavelet:
    """A wavelet matrix: rank and access over a sequence of symbols, one bit vector a level."""

    def __init__(self, sequence: np.ndarray, symbols: int) -> None:
        self.levels = max(1, int(symbols - 1).bit_length())
        self.n = len(sequence)
        self.bits, self.ones, self.zeros = [], [], []
        now = sequence
        for level in range(self.levels - 1, -1, -1):
            bit = (now >> level) & 1
            packed = np.zeros(self.n // 64 + 1, np.uint64)
            raw = np.packbits(bit.astype(bool), bitorder="little")
            packed.view(np.uint8)[: len(raw)] = raw
            self.bits.append(packed)
            self.ones.append(np.append(0, np.cumsum(np.bitwise_count(packed).astype(np.int64))))
            one = bit.astype(bool)
            self.zeros.append(self.n - int(one.sum()))
            now = np.concatenate([now[~one], now[one]])

    def _rank1(self, k: int, at: np.ndarray) -> np.ndarray:
        word, rest = at >> 6, (at & 63).astype(np.uint64)
        return self.ones[k][word] + np.bitwise_count(self.bits[k][word] & ((np.uint64(1) << rest) - np.uint64(1)))

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """How often each symbol stands before place `at`."""
        low = np.zeros_like(at)
        for k in range(self.levels):
            one = (symbol >> (self.levels - 1 - k)) & 1 > 0
            a, b = self._rank1(k, low), self._rank1(k, at)
            low, at = np.where(one, self.zeros[k] + a, low - a), np.where(one, self.zeros[k] + b, at - b)
        return at - low

    def access(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The symbol at each place, and how often it stands before."""
        symbol, low, here = np.zeros_like(at), np.zeros_like(at), at
        for k in range(self.levels):
            one = (self.bits[k][here >> 6] >> (here & 63).astype(np.uint64)) & np.uint64(1) > 0
            a, b = self._rank1(k, low), self._rank1(k, here)
            low, here = np.where(one, self.zeros[k] + a, low - a), np.where(one, self.zeros[k] + b, here - b)
            symbol = symbol * 2 + one
        return symbol, here - low


class ShardIndex:
    """The FM-index of one shard."""

    def __init__(self, text: np.ndarray, symbols: int) -> None:
        order = suffix_array(text)
        self.n = len(text)
        self.before = np.append(0, np.cumsum(np.bincount(text, minlength=symbols)))  # places below each symbol
        self.last = Wavelet(text[order - 1], symbols)  # the symbol before each suffix; the first suffix has the last symbol
        # equal end symbols keep no order among documents, so no walk may cross one: each document start is sampled too
        sampled = (order % SAMPLE == 0) | (text[order - 1] == 0)
        self.sampled = sampled
        self.sample_rank = np.cumsum(sampled) - 1
        self.position = order[sampled]

    def search(self, phrases: Phrases) -> tuple[np.ndarray, np.ndarray]:
        """The range of suffixes that begin with each phrase."""
        count, width = phrases.symbols.shape
        low, high = np.zeros(count, np.int64), np.full(count, self.n, np.int64)
        for j in range(width - 1, -1, -1):
            use = np.flatnonzero((phrases.symbols[:, j] >= 0) & (low < high))
            if len(use):
                c = phrases.symbols[use, j]
                low[use], high[use] = self.before[c] + self.last.rank(c, low[use]), self.before[c] + self.last.rank(c, high[use])
        return low, high

    def locate(self, rows: np.ndarray) -> np.ndarray:
        """Text positions of suffix rows: walk back to a sampled one and add the steps."""
        out, at, steps, who = np.zeros(len(rows), np.int64), rows, 0, np.arange(len(rows))
        while len(who):
            hit = self.sampled[at]
            out[who[hit]] = self.position[self.sample_rank[at[hit]]] + steps
            who, at = who[~hit], at[~hit]
            symbol, rank = self.last.access(at)
            at = self.before[symbol] + rank
            steps += 1
        return out


def search_shard(columns: list[pa.Array], phrases: Phrases) -> list[tuple[int, np.ndarray, np.ndarray]]:
    """For each text of the columns: words, hit words (places), items with an occurrence (numbers)."""
    symbols = len(phrases.known) + _FIRST
    text_parts, place_parts, counts = [], [], []
    for column in columns:
        words = find_words(column, ALNUM, lower=True)
        h = hash_words(words)
        counts.append(words.counts)
        if len(phrases.known):
            at = np.minimum(np.searchsorted(phrases.known, h), len(phrases.known) - 1)
            symbol = np.where(phrases.known[at] == h, at + _FIRST, _OTHER)
        else:
            symbol = np.full(len(h), _OTHER)
        # one end symbol after each text, runs of other words shrink to one
        ends = words.first[1:]
        symbol, place = np.insert(symbol, ends, 0), np.insert(np.arange(len(h)), ends, -1)
        keep = np.append(True, (symbol[1:] != _OTHER) | (symbol[:-1] != _OTHER)) if len(symbol) else np.zeros(0, bool)
        shift = sum(int(c.sum()) for c in counts[:-1])
        text_parts.append(symbol[keep])
        place_parts.append(np.where(place[keep] >= 0, place[keep] + shift, -1))
    n_words = np.concatenate(counts)
    first = np.append(0, np.cumsum(n_words))
    text, place = np.concatenate(text_parts).astype(np.int64), np.concatenate(place_parts)
    total = int(first[-1])
    step = np.zeros(total + 1, np.int64)
    pairs = np.zeros((0, 2), np.int64)
    if total and len(phrases.size) and int(text.max()) >= _FIRST:
        index = ShardIndex(text, symbols)
        low, high = index.search(phrases)
        found = np.flatnonzero(high > low)
        many = (high - low)[found]
        parts = []
        for group in np.array_split(np.arange(len(found)), max(1, int(many.sum()) // 500_000)):
            if not len(group):
                continue
            size = many[group]
            rows = np.repeat(low[found[group]] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))
            window = np.repeat(found[group], size)
            start = place[index.locate(rows)]
            np.add.at(step, start, 1)
            np.add.at(step, start + phrases.size[window], -1)
            doc = np.searchsorted(first, start, side="right") - 1
            parts.append(np.unique(np.stack([doc, window], 1), axis=0))
        if parts:
            pairs = np.unique(np.concatenate(parts), axis=0)
    hit = np.cumsum(step[:-1]) > 0
    edge = np.searchsorted(pairs[:, 0], np.arange(len(n_words) + 1))
    out = []
    for i, n in enumerate(n_words.tolist()):
        windows = pairs[edge[i] : edge[i + 1], 1]
        items = np.unique(np.concatenate([phrases.items[w] for w in windows])) if len(windows) else np.zeros(0, np.int64)
        out.append((n, np.flatnonzero(hit[first[i] : first[i + 1]]), items))
    return out


def _item_blocks(benchmark: DataFrame, key: str, text: str) -> Iterator[list[tuple[str, str]]]:
    """Items in blocks of a bounded size, so that each can be broadcast."""
    rows = benchmark.where(F.col(text).isNotNull()).select(F.coalesce(F.col(key).cast("string"), F.lit("")).alias("k"), F.col(text).alias("t"))
    size = rows.agg(F.sum(F.octet_length("t"))).first()[0] or 0
    blocks = int(size // ITEM_BYTES) + 1
    for i in range(blocks):
        part = rows if blocks == 1 else rows.where(F.pmod(F.xxhash64("k"), F.lit(blocks)) == i)
        yield [(r["k"], r["t"]) for r in part.collect()]


def _shards(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, list[pa.Array]]]:
    """Rows of a task in shards of bounded text: about SHARD words, or one longer text."""
    for b in batches:
        column = as_strings(b.column(1))
        for low, high in slices(column, SHARD * 6):
            yield b.slice(low, high - low), [column.slice(low, high - low)]


def find_contamination(docs: DataFrame, benchmark: DataFrame, width: int = 10, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text") -> DataFrame:
    """One row per document: key, n_words, n_hit, n_items, items_sha256, contaminated."""
    kind = docs.schema[key].dataType.simpleString()

    def report(rows: pa.RecordBatch, results: list[tuple[int, np.ndarray, list[str]]]) -> pa.RecordBatch:
        items = [sorted(r[2]) for r in results]
        return pa.RecordBatch.from_arrays([
            rows.column(0), pa.array([r[0] for r in results], pa.int64()), pa.array([len(r[1]) for r in results], pa.int64()), pa.array([len(i) for i in items], pa.int64()),
            pa.array([hashlib.sha256(",".join(i).encode()).hexdigest() for i in items], pa.string()), pa.array([len(r[1]) > 0 for r in results], pa.bool_()),
        ], [key, "n_words", "n_hit", "n_items", "items_sha256", "contaminated"])

    schema = f"{key} {kind}, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean"
    return _searched(docs.select(F.col(key), F.col(text)), _item_blocks(benchmark, item_key, item_text), width, report, schema)


def remove_contamination(docs: DataFrame, benchmark: DataFrame, width: int = 10, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text") -> DataFrame:
    """All columns of `docs`; texts with hits lose the merged spans of hit words (bytes from the first to the last hit word of a span)."""
    others = [c for c in docs.columns if c != text]

    def cut(rows: pa.RecordBatch, results: list[tuple[int, np.ndarray, list[str]]]) -> pa.RecordBatch:
        texts = rows.column(1)
        hits = [i for i, r in enumerate(results) if len(r[1])]
        if hits:
            out = texts.to_pylist()
            for i in hits:
                out[i] = _without(out[i], results[i][1])
            texts = pa.array(out, pa.string())
        return pa.RecordBatch.from_arrays([rows.column(0), texts, *rows.columns[2:]], rows.schema.names)

    rest = [c for c in others if c != key]
    schema = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in [key, text, *rest])
    return _searched(docs.select(key, text, *rest), _item_blocks(benchmark, item_key, item_text), width, cut, schema).select(*docs.columns)


def _without(text: str, hit: np.ndarray) -> str:
    words = find_words(pa.array([text], pa.string()), ALNUM, lower=True)
    data = text.encode()
    breaks = np.flatnonzero(np.diff(hit) > 1)
    starts, ends = hit[np.append(0, breaks + 1)], hit[np.append(breaks, len(hit) - 1)]
    kept, at = [], 0
    for a, b in zip(words.start[starts].tolist(), words.end[ends].tolist(), strict=True):
        kept.append(data[at:a])
        at = b
    return b"".join([*kept, data[at:]]).decode()


def _searched(rows: DataFrame, blocks: Iterator[list[tuple[str, str]]], width: int, result, schema: str) -> DataFrame:
    """One pass over the rows (key, text, others) a block of items; only one block is broadcast at a time. Passes before
    the last write the rows with what was found so far."""
    context, scratch = rows.sparkSession.sparkContext, Scratch(rows.sparkSession, "decontaminate")
    names, now, block = rows.columns, rows, next(blocks)
    while True:
        after = next(blocks, None)
        phrases = context.broadcast(Phrases.of(block, width))
        if after is None:
            return now.mapInArrow(tidy(_worker(phrases, len(names), result)), schema)
        before, kinds = now, ", ".join(f"`{c}` {rows.schema[c].dataType.simpleString()}" for c in names)
        now = scratch.write(now.mapInArrow(tidy(_worker(phrases, len(names), None)), f"{kinds}, __hit binary, __items array<string>"))
        scratch.drop(before)
        phrases.destroy()
        block = after


def _worker(phrases, width: int, result):
    """Searches one block and merges what earlier blocks found, in two columns after the `width` own ones; result None hands that on."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = phrases.value.names
        for rows, columns in _shards(batches):
            found = [(n, hit, [names[i] for i in items.tolist()]) for n, hit, items in search_shard(columns, phrases.value)]
            own = pa.RecordBatch.from_arrays(rows.columns[:width], rows.schema.names[:width])
            if rows.num_columns > width:
                earlier = zip(rows.column(width).to_pylist(), rows.column(width + 1).to_pylist(), strict=True)
                found = [(n, np.union1d(np.frombuffer(a, "<i8"), hit).astype(np.int64), sorted({*x, *y})) for (n, hit, y), (a, x) in zip(found, earlier, strict=True)]
            if result is None:
                hits = pa.array([hit.astype("<i8").tobytes() for _, hit, _ in found], pa.binary())
                yield pa.RecordBatch.from_arrays([*own.columns, hits, pa.array([x for *_, x in found], pa.list_(pa.string()))], [*own.schema.names, "__hit", "__items"])
            else:
                yield result(own, found)

    return work
