"""Values of distinct stretches of text, computed once per worker and kept in sorted arrays."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

MOST = 2_000_000


class Memo:
    """A bounded cache from a 128-bit fingerprint (two independent 64-bit hashes) to an integer.

    `values` takes the hashes of all stretches and a function that computes the values of the
    stretches at given places; it is called once for those that are not known. A cache that would
    grow over `most` entries is emptied first (`on_clear` tells), which costs time but no result.
    """

    def __init__(self, most: int = MOST, on_clear: Callable[[], None] = lambda: None) -> None:
        self.most, self.on_clear = most, on_clear
        self._empty()

    def _empty(self) -> None:
        self.keys, self.check, self.value = np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.int64)

    def values(self, h: np.ndarray, g: np.ndarray, compute: Callable[[np.ndarray], np.ndarray]) -> np.ndarray:
        order = np.argsort(h, kind="stable")
        ranked = h[order]
        fresh = np.ones(len(h), bool)
        fresh[1:] = ranked[1:] != ranked[:-1]
        first, group = order[fresh], np.cumsum(fresh) - 1
        unique, check = h[first], g[first]
        value, known = np.zeros(len(unique), np.int64), np.zeros(len(unique), bool)
        if len(self.keys):
            at = np.minimum(np.searchsorted(self.keys, unique), len(self.keys) - 1)
            known = (self.keys[at] == unique) & (self.check[at] == check)
            if len(self.keys) + len(unique) - int(known.sum()) > self.most:
                self._empty()
                self.on_clear()
                known[:] = False
            else:
                value[known] = self.value[at[known]]
        new = np.flatnonzero(~known)
        if len(new):
            value[new] = compute(first[new])
            keys = np.concatenate([self.keys, unique[new]])
            by = np.argsort(keys, kind="stable")
            self.keys, self.check, self.value = keys[by], np.concatenate([self.check, check[new]])[by], np.concatenate([self.value, value[new]])[by]
        out = np.empty(len(h), np.int64)
        out[order] = value[group]
        odd = order[g[order] != check[group]]  # equal first fingerprints of different stretches
        if len(odd):
            out[odd] = compute(odd)
        return out
