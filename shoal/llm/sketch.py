"""Count-min sketches of hashed items, gathered per partition, merged, and turned into a bounded filter.

Each partition sketches its items in one very wide row of counters (`2 ** CELL_BITS` cells; a wide row
errs less than several narrow ones of the same size in total). Because few cells of such a row are used
by one partition, the sketch travels sparsely: for each range of cells, the used cells as compressed
differences, and which of them were hit more than once. Partition sketches are merged range by range;
a cell never counts less than the items that fall into it, so every item that occurs twice is found.

What the next pass needs is only which cells count two or more. That is kept as a bitmap of a bounded
size (`bitmap_bits`), broadcast, and asked for each item. Too small a bitmap lets more single items pass
(they are grouped exactly afterwards) but never loses a repeated one. Where asked for, smaller bitmaps
beside it tell cells of `FREQUENT` counts, so items can be put in a rough order of rising frequency.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.broadcast import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shoal.llm.storage import arrow_stage, input_bytes, tidy

CELL_BITS = 34
#: Bounds of the broadcast bitmap: 4 MB and 256 MB.
LEAST_BITS, MOST_BITS = 25, 31
#: Counts from which an item has rank 1, 2, 3; each rank's bitmap has an eighth of the bits of the one before.
FREQUENT = (16, 128, 1024)
#: Items that a partition gathers before it hands its sketch on.
FLUSH = 4_000_000


def pack(numbers: np.ndarray) -> bytes:
    """Unsigned numbers, compressed with their byte planes apart."""
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(numbers).view(np.uint8).reshape(-1, numbers.itemsize).T.tobytes())


def unpack(blob: bytes, kind: type) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(blob), np.uint8)
    return np.ascontiguousarray(planes.reshape(np.dtype(kind).itemsize, -1).T).view(kind).ravel()


def pack_rising(numbers: np.ndarray) -> bytes:
    """Rising numbers as differences."""
    return pack(np.diff(numbers, prepend=numbers.dtype.type(0)))


def unpack_rising(blob: bytes, kind: type) -> np.ndarray:
    return np.cumsum(unpack(blob, kind), dtype=kind)


def shape(size: int) -> tuple[int, int]:
    """Bits that name a range of cells, and bits of the bitmap, for so many bytes of input."""
    ranges = int(np.clip(np.ceil(np.log2(max(size, 1) / 2**18)), 10, 20))
    bitmap = int(np.clip(np.ceil(np.log2(max(size, 1) / 4)), LEAST_BITS, MOST_BITS))
    return ranges, bitmap


class Repeated:
    """Answers which 64-bit hashes fall into cells that count two or more, and how frequent those are."""

    def __init__(self, bitmaps: Broadcast, bits: list[int]) -> None:
        self.bitmaps, self.bits = bitmaps, bits
        self._bytes: np.ndarray | None = None

    def __getstate__(self):
        return self.bitmaps, self.bits

    def __setstate__(self, state) -> None:
        self.bitmaps, self.bits = state
        self._bytes = None

    def _marked(self, k: int, h: np.ndarray) -> np.ndarray:
        if self._bytes is None:
            self._bytes = np.frombuffer(self.bitmaps.value, np.uint8)
        begin = sum(2**bits // 8 for bits in self.bits[:k])
        at = h >> np.uint64(64 - self.bits[k])
        return (self._bytes[begin:][at >> np.uint64(3)] >> (at & np.uint64(7)).astype(np.uint8)) & np.uint8(1) > 0

    def __call__(self, h: np.ndarray) -> np.ndarray:
        return self._marked(0, h)

    def rank(self, h: np.ndarray) -> np.ndarray:
        """0 for rare items up to the number of bitmaps for the most frequent ones; the same for a hash everywhere."""
        out = np.zeros(len(h), np.uint8)
        for k in range(1, len(self.bits)):
            out[self._marked(k, h)] = k
        return out


def repeated_items(df: DataFrame, columns: list, items: Callable[[pa.RecordBatch], Iterator[np.ndarray]], ranked: bool = False) -> Repeated:
    """Sketches all items of `df` and returns the filter. `items` yields arrays of 64-bit hashes for a batch; `ranked` adds their ranks."""
    ranges, bitmap = shape(input_bytes(df))
    bitmap = max(bitmap, ranges + 3)
    inner = CELL_BITS - ranges  # bits of a cell inside its range
    # bits of a range in each bitmap: cells that count two or more, then those of the ranks
    least = (2, *FREQUENT) if ranked else (2,)
    slice_bits = [max(3, bitmap - ranges - 3 * k) for k in range(len(least))]

    def flush(cells: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        if not cells:
            return
        cell = np.concatenate(cells)
        cells.clear()  # arrays go as soon as they are used: every core has a worker that does this
        cell.sort()
        fresh = np.ones(len(cell), bool)
        fresh[1:] = cell[1:] != cell[:-1]
        unique = cell[fresh]
        del cell
        hits = np.diff(np.flatnonzero(np.append(fresh, True)))
        del fresh
        again = hits > 1
        times = np.minimum(hits, 65535).astype(np.uint16)
        del hits
        edges = np.searchsorted(unique, np.arange(2**ranges + 1, dtype=np.uint64) << np.uint64(inner))
        some = np.flatnonzero(np.diff(edges) > 0)
        low = (unique & np.uint64((1 << inner) - 1)).astype(np.uint32)
        del unique
        parts = [(low[a:b], again[a:b], times[a:b]) for a, b in zip(edges[some].tolist(), edges[some + 1].tolist(), strict=True)]
        yield pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array([pack_rising(p) for p, _, _ in parts], pa.binary()), pa.array([pack_rising(p[q]) for p, q, _ in parts], pa.binary()), pa.array([pack(t[q]) if ranked else None for _, q, t in parts], pa.binary())], ["cells", "used", "more", "times"])

    def sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for b in batches:
            for h in items(b):
                held.append(h >> np.uint64(64 - CELL_BITS))
                n += len(h)
                if n >= FLUSH:
                    yield from flush(held)
                    held, n = [], 0
        yield from flush(held)

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Partitions are sorted by range, so the counts of one range at a time are held, as those cells only."""
        at, used, more, times = None, [], [], []

        def done() -> Iterator[pa.RecordBatch]:
            if at is None:
                return
            cell = np.concatenate(used)
            cell.sort()
            if ranked:
                begin = np.flatnonzero(np.append(True, cell[1:] != cell[:-1]))
                unique, count = cell[begin], np.diff(np.append(begin, len(cell)))
                for m, t in zip(more, times, strict=True):
                    count[np.searchsorted(unique, m)] += t.astype(np.int64) - 1
                hot = [unique[count >= n] for n in least]
            else:
                hot = [np.concatenate([cell[1:][cell[1:] == cell[:-1]], *more])]
            out = []
            for cells, wide in zip(hot, slice_bits, strict=True):
                bits = np.zeros(2**wide, bool)
                bits[cells >> np.uint32(max(0, inner - wide))] = True
                out.append(np.packbits(bits, bitorder="little").tobytes())
            yield pa.RecordBatch.from_arrays([pa.array([at], pa.int32()), pa.array([zstandard.ZstdCompressor(level=1).compress(b"".join(out))], pa.binary())], ["cells", "bits"])

        for b in batches:
            for c, u, m, t in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                if c != at:
                    yield from done()
                    at, used, more, times = c, [], [], []
                used.append(unpack_rising(u, np.uint32))
                more.append(unpack_rising(m, np.uint32))
                if ranked:
                    times.append(unpack(t, np.uint16))
        yield from done()

    sketches = arrow_stage(df, columns, sketch, "cells int, used binary, more binary, times binary")
    merged = sketches.repartition(F.col("cells")).sortWithinPartitions("cells").mapInArrow(tidy(merge), "cells int, bits binary")
    widths = [2**bits // 8 for bits in slice_bits]
    whole = np.zeros(2**ranges * sum(widths), np.uint8)
    cuts = np.cumsum(widths)[:-1]
    tables = [t.reshape(2**ranges, -1) for t in np.split(whole, cuts * 2**ranges)]
    undo = zstandard.ZstdDecompressor()
    for row in merged.toLocalIterator(prefetchPartitions=True) if bitmap > 29 else merged.collect():
        for table, part in zip(tables, np.split(np.frombuffer(undo.decompress(bytes(row["bits"])), np.uint8), cuts), strict=True):
            table[row["cells"]] = part
    return Repeated(df.sparkSession.sparkContext.broadcast(whole.tobytes()), [ranges + bits for bits in slice_bits])
