"""Encoding and decoding with a merge-type piece vocabulary (BPE with byte fallback) through a prefix table.

For every prefix of a stretch of text, the encoding of that prefix ends in one certain token. The
table of those last tokens is filled from left to right: the tokens that end at a position come from
an automaton over the reversed pieces, and the right one is the one that can stand behind the last
token of the prefix it leaves (`stands`: merging the two strings again gives just the pair). The ids
are then recovered backwards from the last entry. No priority queue over the text is needed.

Texts are cut beforehand where no piece reaches across: before a blank that follows a letter, and
around characters that no longer piece contains. Distinct stretches are encoded together, position
by position, in numpy; stretches of over `LONG` characters singly. Runs of blanks have their own rule,
because all run pieces share one score (`run_ids`).
"""

from __future__ import annotations

import hashlib
import heapq
import re
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shoal.llm.memo import Memo
from shoal.llm.storage import arrow_stage, give_back
from shoal.llm.words import Words, as_strings, byte_class, find_words, hash_words, raw, slices

BLANK = "▁"
LONG = 200
KEPT = 1_000_000  # units kept per worker, about 60 MB
SLICE = 2 << 20  # bytes of text encoded at once
TOGETHER = 30_000  # units encoded at once
CELLS = 2_000_000  # cells of the prefix tables filled together, 10 bytes each
#: Fixed values of the model file format: kinds of pieces.
NORMAL, UNKNOWN, CONTROL, BYTE = 1, 2, 3, 6
_UNBROKEN = byte_class([(0x20, 0x20), (0x0A, 0x0A)])
_K1 = np.uint64(0x9E3779B97F4A7C15)
_READY: dict[str, PieceTable] = {}


class PieceTable:
    def __init__(self, path: str) -> None:
        from sentencepiece import sentencepiece_model_pb2 as pb

        model = pb.ModelProto()
        model.ParseFromString(open(path, "rb").read())
        spec = model.normalizer_spec
        if model.trainer_spec.model_type != 2 or not model.trainer_spec.byte_fallback or spec.precompiled_charsmap or spec.remove_extra_whitespaces or not spec.add_dummy_prefix:
            raise ValueError("only merge-type models with byte fallback, a dummy prefix and no normalisation are supported")
        self.id = {p.piece: i for i, p in enumerate(model.pieces) if p.type == NORMAL}
        self.score = {p.piece: p.score for p in model.pieces if p.type == NORMAL}
        self.byte = {int(p.piece[1:-1], 16): i for i, p in enumerate(model.pieces) if p.type == BYTE}
        kinds = [p.type for p in model.pieces]
        self.begin, self.end = (next(i for i, p in enumerate(model.pieces) if p.piece == s and p.type == CONTROL) for s in ("<s>", "</s>"))
        self.text = [p.piece for p in model.pieces]
        #: What each id stands for when decoded: bytes; None for control ids.
        value = {i: b for b, i in self.byte.items()}
        self.unknown = next((i for i, k in enumerate(kinds) if k == UNKNOWN), -1)
        mark = BLANK.encode()
        shown = [bytes([value[i]]) if k == BYTE else b"" if k == CONTROL else " ⁇ ".encode() if k == UNKNOWN else p.piece.encode().replace(mark, b" ") for i, (p, k) in enumerate(zip(model.pieces, kinds, strict=True))]
        self.value_size = np.array([len(b) for b in shown], np.int64)
        self.value_at, self.value_bytes = np.cumsum(self.value_size) - self.value_size, np.frombuffer(b"".join(shown), np.uint8)
        longer = [p for p in self.id if len(p) > 1 and p.strip(BLANK)]
        if any(BLANK in p[1:] for p in longer):
            raise ValueError("a piece holds a blank inside")
        self.letters = sorted({c for p in longer for c in p} - {BLANK})
        inner = re.escape("".join(self.letters))
        self.cut = re.compile(f"{BLANK}?[{inner}]+|{BLANK}+(?![{inner}])|.", re.DOTALL)
        self.memo = Memo(KEPT, self._forget)
        self._forget()
        self._known_pair = lru_cache(100_000)(self.stands)
        self.runs: dict[int, tuple[int, ...]] = {}
        self._automaton([p for p in self.id if set(p) <= {*self.letters, BLANK} and (len(p) == 1 or p.strip(BLANK))])
        self._pair_keys, self._pair_ok = np.zeros(0, np.int64), np.zeros(0, bool)

    # -- merging by definition: used for single pieces, for pairs and for runs of blanks ---------------

    def merge(self, text: str) -> list[str]:
        """The encoding by definition: join the neighbours of best score, leftmost first, until none is a piece."""
        parts: list[str | None] = list(text)
        after, before = [*range(1, len(parts)), -1], [*range(-1, len(parts) - 1)]
        heap = [(-self.score[p], i, p) for i in range(len(parts) - 1) if (p := text[i : i + 2]) in self.score]
        heapq.heapify(heap)
        while heap:
            _, i, joined = heapq.heappop(heap)
            j = after[i]
            if parts[i] is None or j < 0 or parts[i] + parts[j] != joined:
                continue
            parts[i], parts[j], after[i] = joined, None, after[j]
            if after[j] >= 0:
                before[after[j]] = i
            for left in (before[i], i):
                if left >= 0 and (right := after[left]) >= 0 and (p := parts[left] + parts[right]) in self.score:
                    heapq.heappush(heap, (-self.score[p], left, p))
        return [p for p in parts if p is not None]

    def stands(self, left: int, right: int) -> bool:
        """Whether the token `right` can stand directly behind `left` (-1: at the beginning)."""
        want = [self.text[right]] if left < 0 else [self.text[left], self.text[right]]
        return self.merge("".join(want)) == want

    def run_ids(self, n: int) -> tuple[int, ...]:
        if n not in self.runs:
            if len(self.runs) > 10_000:
                self.runs.clear()
            self.runs[n] = tuple(self.id[p] for p in self.merge(BLANK * n))
        return self.runs[n]

    # -- the automaton ---------------------------------------------------------------------------------

    def _automaton(self, pieces: list[str]) -> None:
        """A trie of the reversed pieces as a dense table over the few characters that longer pieces use."""
        self.column = {c: k + 1 for k, c in enumerate([BLANK, *self.letters])}
        step: list[dict[int, int]] = [{}]
        token = [-1]
        for piece in pieces:
            node = 0
            for c in reversed(piece):
                k = self.column[c]
                if k not in step[node]:
                    step[node][k] = len(step)
                    step.append({})
                    token.append(-1)
                node = step[node][k]
            token[node] = self.id[piece]
        inner = [n for n, s in enumerate(step) if s]
        row = np.zeros(len(step), np.int32)  # row 0: no way on
        row[inner] = np.arange(1, len(inner) + 1)
        self.row, self.token = row, np.array(token, np.int32)
        self.next = np.zeros((len(inner) + 1, len(self.column) + 1), np.int32)
        for n in inner:
            for k, to in step[n].items():
                self.next[row[n], k] = to
        self.deepest = max(map(len, pieces))
        self.column_of = np.zeros(max(map(ord, self.column)) + 1, np.int32)
        for c, k in self.column.items():
            self.column_of[ord(c)] = k

    def _stand(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """`stands` for arrays; new pairs are tested once and kept in a sorted table."""
        key = (left.astype(np.int64) + 1) * len(self.text) + right
        if len(self._pair_keys):
            at = np.minimum(np.searchsorted(self._pair_keys, key), len(self._pair_keys) - 1)
            missing = np.unique(key[self._pair_keys[at] != key])
        else:
            missing = np.unique(key)
        if len(missing):
            ok = np.array([self.stands(k // len(self.text) - 1, k % len(self.text)) for k in missing.tolist()], bool)
            keys = np.concatenate([self._pair_keys, missing])
            order = np.argsort(keys, kind="stable")
            self._pair_keys, self._pair_ok = keys[order], np.concatenate([self._pair_ok, ok])[order]
            at = np.searchsorted(self._pair_keys, key)
        return self._pair_ok[at]

    # -- encoding --------------------------------------------------------------------------------------

    def _together(self, stretches: list[str]) -> list[tuple[int, ...]]:
        """Fills the prefix tables of many stretches of known letters at once, longest first."""
        order = sorted(range(len(stretches)), key=lambda i: -len(stretches[i]))
        size = np.array([len(stretches[i]) for i in order])
        width, n = int(size[0]), len(order)
        flat = np.frombuffer("".join(stretches[i] for i in order).encode("utf-32-le"), "<u4")
        column = np.zeros((width, n), np.int32)
        where = np.repeat(np.arange(n), size)
        column[np.arange(len(flat)) - np.repeat(np.cumsum(size) - size, size), where] = self.column_of[flat]
        last, back = np.full((width + 1, n), -1, np.int32), np.zeros((width + 1, n), np.int16)
        live_at = n - np.searchsorted(size[::-1], np.arange(1, width + 1), side="left")
        for p in range(1, width + 1):
            live = int(live_at[p - 1])
            who, node, found = np.arange(live), np.zeros(live, np.int32), []
            for d in range(1, min(p, self.deepest) + 1):
                node = self.next[self.row[node], column[p - d, who]]
                on = node > 0
                who, node = who[on], node[on]
                if not len(who):
                    break
                hit = self.token[node] >= 0
                found.append((d, who[hit], self.token[node[hit]]))
            for d, who, token in reversed(found):
                free = back[p, who] == 0
                who, token = who[free], token[free]
                if len(who):
                    ok = self._stand(last[p - d, who], token)
                    last[p, who[ok]], back[p, who[ok]] = token[ok], d
        out: list[list[int]] = [[] for _ in range(n)]
        at, who, steps = size.copy(), np.arange(n), []
        while len(who):
            steps.append((who, last[at[who], who]))
            at[who] -= back[at[who], who]
            who = who[at[who] > 0]
        for who, token in reversed(steps):
            for w, t in zip(who.tolist(), token.tolist(), strict=True):
                out[w].append(t)
        result: list[tuple[int, ...]] = [()] * n
        for k, i in enumerate(order):
            result[i] = tuple(out[k])
        return result

    def _single(self, text: str) -> tuple[int, ...]:
        """One prefix table, for a long stretch."""
        column = [self.column[c] for c in text]
        last, back = [-1] * (len(text) + 1), [0] * (len(text) + 1)
        for p in range(1, len(text) + 1):
            node, found = 0, []
            for d in range(1, min(p, self.deepest) + 1):
                node = int(self.next[self.row[node], column[p - d]])
                if not node:
                    break
                if (t := int(self.token[node])) >= 0:
                    found.append((d, t))
            for d, t in reversed(found):
                if self._known_pair(last[p - d], t):
                    last[p], back[p] = t, d
                    break
        out, p = [], len(text)
        while p:
            out.append(last[p])
            p -= back[p]
        return tuple(reversed(out))

    def _other(self, c: str) -> tuple[int, ...]:
        return (self.id[c],) if c in self.id else tuple(self.byte[b] for b in c.encode("utf-8", "surrogatepass"))

    def _stretches(self, cuts: list[list[str]]) -> dict[str, tuple[int, ...]]:
        """The ids of every distinct stretch."""
        known, joint = {}, []
        for s in sorted(set().union(*cuts)):
            if s[-1] == BLANK:
                known[s] = self.run_ids(len(s))
            elif s[-1] not in self.column:
                known[s] = self._other(s)
            elif len(s) > LONG:
                known[s] = self._single(s)
            else:
                joint.append(s)
        joint.sort(key=len)  # a table is as wide as its longest stretch
        while joint:
            part = joint[-max(1, CELLS // len(joint[-1])) :]
            del joint[-len(part) :]
            known.update(zip(part, self._together(part), strict=True))
        return known

    def strings(self, texts: list[str]) -> list[list[int]]:
        """Ids of texts whose blanks are marked already; no begin or end id."""
        cuts = [self.cut.findall(t) for t in texts]
        known, blank, out = self._stretches(cuts), self.id[BLANK], []
        for cut in cuts:
            ids: list[int] = []
            run = 0  # length of the run of blanks just added
            for s in cut:
                got = known[s]
                if run and got[0] == blank and s[0] == BLANK and len(s) > 1 and s[1] != BLANK:
                    # the stretch's own blank stays single, so it takes part in the run before it
                    del ids[-len(self.run_ids(run)) :]
                    ids += self.run_ids(run + 1)
                    ids += got[1:]
                else:
                    ids += got
                run = len(s) if s[-1] == BLANK else 0
            out.append(ids)
        return out

    # -- whole columns ---------------------------------------------------------------------------------

    def _forget(self) -> None:
        self.pool, self.pool_at, self.pool_size = np.zeros(0, np.int32), np.zeros(0, np.int64), np.zeros(0, np.int32)

    def _pool(self, units: list[str]) -> np.ndarray:
        low, sizes, ids = len(self.pool_at), [], []
        for i in range(0, len(units), TOGETHER):
            found = self.strings(units[i : i + TOGETHER])
            sizes.append(np.fromiter(map(len, found), np.int32, len(found)))
            ids.append(np.fromiter(chain.from_iterable(found), np.int32, int(sizes[-1].sum())))
        size = np.concatenate([np.zeros(0, np.int32), *sizes])
        self.pool_at = np.concatenate([self.pool_at, len(self.pool) + np.cumsum(size, dtype=np.int64) - size])
        self.pool_size = np.concatenate([self.pool_size, size])
        self.pool = np.concatenate([self.pool, *ids])
        return np.arange(low, low + len(units))

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids of a slice of texts, and where each text's ids begin. A unit is a word with the blanks
        before it; units repeat, so each distinct one is encoded once."""
        body, off = raw(column)
        words = find_words(column, _UNBROKEN)
        marked = np.zeros(len(column), bool)  # texts that hold the blank mark itself are encoded whole
        if BLANK.encode() in body.tobytes():
            marked = pc.match_substring(column, BLANK).to_numpy(zero_copy_only=False)
        # a unit begins where the word before it ended; what follows the last word is a unit too
        start, end, text = words.start.copy(), words.end, words.text
        start[1:] = words.end[:-1]
        some = words.counts > 0
        start[words.first[:-1][some]] = off[:-1][some]
        last = np.where(some, end[np.maximum(words.first[1:] - 1, 0)] if len(end) else 0, off[:-1])
        rest = np.flatnonzero(last < off[1:])
        start, end, text = (np.insert(a, words.first[1:][rest], b) for a, b in ((start, last[rest]), (end, off[1:][rest]), (text, rest)))
        use = ~marked[text]
        start, end, text = start[use], end[use], text[use]
        opens = start == off[text]
        units = Words(words.data, start, end, text, np.searchsorted(text, np.arange(len(column) + 1)))
        tweak = np.where(opens, _K1, np.uint64(0))

        def compute(new: np.ndarray) -> np.ndarray:
            return self._pool([(BLANK if o else "") + units.string(i).decode().replace(" ", BLANK) for i, o in zip(new.tolist(), opens[new].tolist(), strict=True)])

        place = self.memo.values(hash_words(units) ^ tweak, hash_words(units, 1) ^ tweak, compute) if len(units) else np.zeros(0, np.int64)
        whole = np.flatnonzero(marked)
        if len(whole):
            extra = self._pool([BLANK + column[int(i)].as_py().replace(" ", BLANK) for i in whole])
            where = np.searchsorted(text, whole)
            place, text = np.insert(place, where, extra), np.insert(text, where, whole)
        n = self.pool_size[place].astype(np.int64)
        own = np.bincount(text, weights=n, minlength=len(column)).astype(np.int64) if len(n) else np.zeros(len(column), np.int64)
        first = np.concatenate([[0], np.cumsum(own + 2)])
        ids = np.empty(int(first[-1]), np.int32)
        ids[first[:-1]], ids[first[1:] - 1] = self.begin, self.end
        inside = np.ones(len(ids), bool)
        inside[first[:-1]] = inside[first[1:] - 1] = False
        if len(n):
            ids[inside] = self.pool[np.repeat(self.pool_at[place] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))]
        return ids, first

    def encode_batch(self, texts: list[str | None]) -> list[list[int]]:
        """Ids of each text, with begin and end ids."""
        column = as_strings(pa.array(texts, pa.string()))
        ids, first = self.encode(column)
        return [ids[a:b].tolist() for a, b in zip(first[:-1], first[1:], strict=True)]

    def decode_all(self, ids: np.ndarray, first: np.ndarray) -> list[bytes]:
        """Texts of many id sequences in UTF-8: control ids vanish, byte ids form UTF-8, one leading blank goes."""
        size = self.value_size[ids]
        ends = np.concatenate([[0], np.cumsum(size)])
        place = np.repeat(self.value_at[ids] - ends[:-1], size)
        place += np.arange(int(ends[-1]))
        data = self.value_bytes[place].tobytes()
        cut = ends[first].tolist()
        return [data[a:b].removeprefix(b" ").decode("utf-8", "replace").encode() for a, b in zip(cut[:-1], cut[1:], strict=True)]

    def decode(self, ids: list[int]) -> str:
        return self.decode_all(np.array(ids, np.int64), np.array([0, len(ids)]))[0].decode()


def table(path: str) -> PieceTable:
    if path not in _READY:
        _READY[path] = PieceTable(path)
    return _READY[path]


def encode_documents(docs: DataFrame, model: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per text: key, ids array<int>, decoded string. Null texts count as empty ones: begin and end id only."""

    def lists(ids: np.ndarray, first: np.ndarray, decoded: list[bytes]) -> list[pa.Array]:
        return [pa.ListArray.from_arrays(pa.array(first, pa.int32()), pa.array(ids, pa.int32())), pa.array([d.decode() for d in decoded], pa.string())]

    return _stage(docs, model, key, text, f"{key} {docs.schema[key].dataType.simpleString()}, ids array<int>, decoded string", lists)


def encoding_digests(docs: DataFrame, model: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per text: key, n_tokens, ids_sha256, decoded_sha256; the ids stay on the worker."""

    def digests(ids: np.ndarray, first: np.ndarray, decoded: list[bytes]) -> list[pa.Array]:
        each = [hashlib.sha256(ids[a:b].astype("<u4").tobytes()).hexdigest() for a, b in zip(first[:-1], first[1:], strict=True)]
        return [pa.array(np.diff(first), pa.int64()), pa.array(each, pa.string()), pa.array([hashlib.sha256(d).hexdigest() for d in decoded], pa.string())]

    return _stage(docs, model, key, text, f"{key} {docs.schema[key].dataType.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string", digests)


def _stage(docs: DataFrame, model: str, key: str, text: str, schema: str, result) -> DataFrame:
    names = [x.strip().split(" ")[0] for x in schema.split(", ")]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool = table(model)
        for b in batches:
            column = as_strings(b.column(1))
            for low, high in slices(column, SLICE):
                ids, first = tool.encode(column.slice(low, high - low))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(low, high - low), *result(ids, first, tool.decode_all(ids, first))], names)
                give_back()

    return arrow_stage(docs, [F.col(key), F.col(text)], work, schema)
