"""Words and their fingerprints for whole Arrow string columns, without a Python loop over words.

A text column arrives as one byte buffer with offsets. A 256-entry table says which bytes belong to
words, so runs of such bytes are the words; a word is hashed eight bytes at a time through an
unaligned 64-bit view. Every function works on bounded slices of a batch (`slices`), so memory
depends on the slice (or on the longest single text), never on the partition.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

SLICE_BYTES = 4 << 20


def byte_class(separators: list[tuple[int, int]]) -> np.ndarray:
    """A table that is True for bytes inside words; bytes from 0x80 on (non-ASCII) always are."""
    inside = np.ones(256, bool)
    for low, high in separators:
        inside[low : high + 1] = False
    return inside


#: Words are runs of anything but blank, tab, LF, VT, FF and CR.
PLAIN = byte_class([(0x20, 0x20), (0x09, 0x0D)])
#: Words are runs of digits, a-z and non-ASCII characters (after lower-casing A-Z).
ALNUM = byte_class([(0x00, 0x2F), (0x3A, 0x60), (0x7B, 0x7F)])
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


@dataclass
class Words:
    """Words of some texts: `data` holds the bytes (padded by 8), a word is data[start:end]."""

    data: np.ndarray
    start: np.ndarray
    end: np.ndarray
    text: np.ndarray  # index of the word's text
    first: np.ndarray  # index of each text's first word; one entry more than texts

    def __len__(self) -> int:
        return len(self.start)

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def string(self, i: int) -> bytes:
        return self.data[self.start[i] : self.end[i]].tobytes()


def as_strings(column: pa.Array) -> pa.Array:
    """The column with empty strings for nulls, as one array of type string or large_string."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.fill_null("") if column.null_count else column


def raw(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (from 0) of a string array without nulls."""
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    n = len(column)
    _, offsets, data = column.buffers()
    if n == 0 or offsets is None:
        return np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
    off = np.frombuffer(offsets, kind, count=n + 1, offset=column.offset * np.dtype(kind).itemsize).astype(np.int64)
    size = int(off[-1] - off[0])
    body = np.frombuffer(data, np.uint8, count=size, offset=int(off[0])) if size else np.zeros(0, np.uint8)
    return body, off - off[0]


def slices(column: pa.Array, most: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of at most `most` bytes; a longer text stands alone."""
    _, off = raw(column)
    low = 0
    while low < len(column):
        high = max(low + 1, int(np.searchsorted(off, off[low] + most, side="right")) - 1)
        yield low, high
        low = high


def find_words(column: pa.Array, inside: np.ndarray, lower: bool = False) -> Words:
    body, off = raw(column)
    data = np.zeros(len(body) + 8, np.uint8)
    data[:-8] = LOWER[body] if lower else body
    mask = inside[data[:-8]]
    before = np.zeros(len(mask), bool)
    before[1:] = mask[:-1]
    edges = off[:-1][np.diff(off) > 0]
    before[edges] = False  # a text never continues the word before it
    start = np.flatnonzero(mask & ~before)
    after = np.zeros(len(mask), bool)
    after[:-1] = mask[1:]
    after[edges[1:] - 1] = False
    end = np.flatnonzero(mask & ~after) + 1
    first = np.searchsorted(start, off)
    text = np.repeat(np.arange(len(column)), np.diff(first))
    return Words(data, start, end, text, first)


_K1, _K2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)
_S29, _S32 = np.uint64(29), np.uint64(32)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit."""
    x = (x ^ (x >> _S32)) * _K1
    x = (x ^ (x >> _S29)) * _K2
    return x ^ (x >> _S32)


def hash_words(words: Words, seed: int = 0) -> np.ndarray:
    """A 64-bit hash of each word, the same on every machine."""
    size = (words.end - words.start).astype(np.int64)
    out = mix(size.astype(np.uint64) + np.uint64(seed * 0x51ED270B + 1))
    if not len(out):
        return out
    eight = np.ndarray((len(words.data) - 7,), "<u8", words.data, strides=(1,))
    live, at, left = None, words.start, size
    while True:
        keep = np.minimum(left, 8).astype(np.uint64) * np.uint64(8)
        chunk = eight[at] & ((~np.uint64(0)) >> (np.uint64(64) - keep))
        if live is None:
            out = mix(out ^ chunk)
            live = np.flatnonzero(left > 8)
            at, left = at[live] + 8, left[live] - 8
        else:
            out[live] = mix(out[live] ^ chunk)
            more = left > 8
            live, at, left = live[more], at[more] + 8, left[more] - 8
        if not len(live):
            return out


def hash_windows(words: Words, hashes: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Start words of the n-word windows inside one text, and the windows' hashes."""
    m = len(hashes) - n + 1
    if m <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    whole = words.text[:m] == words.text[n - 1 :]
    total = np.zeros(m, np.uint64)
    for j in range(n):
        total *= _K1
        total += hashes[j : j + m]
    at = np.flatnonzero(whole)
    return at, mix(total[at] ^ np.uint64(n))
