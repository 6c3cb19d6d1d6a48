"""Token counts of a word-end BPE vocabulary by the whole-token shortcut.

Offline (once per worker): a vocabulary entry that ends with the word-end mark is *whole* if the
merge rules rebuild it as one token from its own letters. Counting: a text falls into pieces between
ASCII blanks (no pre-token reaches over one), each distinct piece of a slice is handled once: its
pre-tokens that are whole count 1 without any merge, only the others are merged. Counts are then
summed per text over the pieces' fingerprints.

Defined results: null and empty texts have no tokens; strings of special tokens inside a text count
as the library counts them (one token each); texts of any length are counted whole.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shoal.llm.memo import Memo
from shoal.llm.storage import arrow_stage
from shoal.llm.words import PLAIN, as_strings, find_words, hash_words, slices

_READY: dict[str, WholeTokenCounter] = {}
#: Pieces of printable ASCII and Latin-1 letters need no library call to be normalised and cut: they are
#: composed already, hold no blanks, and lower-case letter by letter.
_EASY = re.compile("[!-~\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+")
#: Fixed value: how the vocabulary cuts such (lower-case) pieces into pre-tokens.
_CUT = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-z\u00df-\u00f6\u00f8-\u00ff]+|[0-9]|[^a-z\u00df-\u00f6\u00f8-\u00ff0-9]+")


class WholeTokenCounter:
    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        spec = json.load(open(path))
        library = Tokenizer.from_file(path)
        self.model, self.normalize = library.model, library.normalizer.normalize_str
        self.pre_tokenize = library.pre_tokenizer.pre_tokenize_str
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.whole = self.prove_whole(spec["model"])
        self.merged: dict[str, int] = {}
        visible = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
        hidden = iter(range(256, 512))
        self.letter = {b: chr(b) if b in visible else chr(next(hidden)) for b in range(256)}  # the byte-level alphabet, in Latin-1 order
        self.memo = Memo()

    @staticmethod
    def prove_whole(model: dict) -> frozenset[str]:
        """Pre-tokens that encode alone as one token: for each, replay its merges and see one token remain."""
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        order, end = {p: i for i, p in enumerate(pairs)}, model["end_of_word_suffix"]
        out = set()
        for token in model["vocab"]:
            if not token.endswith(end) or token == end:
                continue
            letters = token[: -len(end)]
            parts = [*letters[:-1], letters[-1] + end]
            while len(parts) > 1:
                best = min(range(len(parts) - 1), key=lambda i: order.get((parts[i], parts[i + 1]), 1 << 60))
                if (parts[best], parts[best + 1]) not in order:
                    break
                parts[best : best + 2] = [parts[best] + parts[best + 1]]
            if parts == [token]:
                out.add(letters)
        return frozenset(out)

    def count(self, piece: str) -> int:
        """Tokens of a text without ASCII blanks inside (or of any text)."""
        n = 0
        for mark in self.special:
            if mark in piece:
                head, _, tail = min((piece.partition(m) for m in self.special if m in piece), key=lambda p: len(p[0]))
                return (self.count(head) if head else 0) + 1 + (self.count(tail) if tail else 0)
        if _EASY.fullmatch(piece):
            for pre in _CUT.findall(piece.lower()):
                n += self.merge(pre if pre.isascii() else pre.encode().decode("latin-1").translate(self.letter))
        else:
            for pre, _ in self.pre_tokenize(self.normalize(piece)):
                n += self.merge(pre)
        return n

    def merge(self, pre: str) -> int:
        """Tokens of a pre-token in the byte-level alphabet."""
        if pre in self.whole:
            return 1
        if (n := self.merged.get(pre)) is None:
            if len(self.merged) > 1_000_000:
                self.merged.clear()
            n = self.merged[pre] = len(self.model.tokenize(pre))
        return n

    def counts(self, column: pa.Array) -> np.ndarray:
        words = find_words(column, PLAIN)
        if not len(words):
            return np.zeros(len(column), np.int64)
        each = self.memo.values(hash_words(words), hash_words(words, 1), lambda new: np.array([self.count(words.string(i).decode()) for i in new], np.int64))
        total = np.concatenate([[0], np.cumsum(each)])
        return total[words.first[1:]] - total[words.first[:-1]]


def counter(path: str) -> WholeTokenCounter:
    if path not in _READY:
        _READY[path] = WholeTokenCounter(path)
    return _READY[path]


def count_tokens(docs: DataFrame, vocabulary: str, limit: int = 2048, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per text: key, n_bytes, n_tokens, over_limit. `vocabulary` is a path that every executor has."""
    kind = docs.schema[key].dataType.simpleString()

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool = counter(vocabulary)
        for b in batches:
            column = as_strings(b.column(1))
            for low, high in slices(column):
                part = column.slice(low, high - low)
                n = tool.counts(part)
                size = pa.compute.binary_length(part).cast(pa.int64())
                yield pa.RecordBatch.from_arrays([b.column(0).slice(low, high - low), size, pa.array(n, pa.int64()), pa.array(n > limit)], [key, "n_bytes", "n_tokens", "over_limit"])

    return arrow_stage(docs, [F.col(key), F.col(text)], work, f"{key} {kind}, n_bytes long, n_tokens long, over_limit boolean")
