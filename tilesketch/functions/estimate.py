"""Size estimates from bottom-k lists, as Column expressions, and the same over NumPy arrays."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from tilesketch.functions.hashing import PRIME


def size(hashes: Column, k: int, prime: int = PRIME, small: str = "exact", estimator: str = "k") -> Column:
    """Estimated number of cells behind one ascending list: k over the k-th smallest hash as a fraction.  A list of fewer
    than k values is complete: its length (``exact``) or null (``discard``)."""
    top = float(k if estimator == "k" else k - 1)
    short = F.size(hashes).cast("double") if small == "exact" else F.lit(None).cast("double")
    return F.when(F.size(hashes) < k, short).otherwise(F.lit(top) / ((F.try_element_at(hashes, F.lit(k)) + 1) / F.lit(float(prime))))


def merge(a: Column, b: Column, k: int, how: str = "union") -> Column:
    """The k smallest of two lists; ``concat`` keeps a value twice that both hold (an ablation)."""
    both = F.array_union(a, b) if how == "union" else F.concat(a, b)
    return F.slice(F.array_sort(both), 1, k)


def joint(a: Column, b: Column, k: int, prime: int = PRIME, how: str = "union", small: str = "exact", estimator: str = "k") -> Column:
    return size(merge(a, b, k, how), k, prime, small, estimator)


def median_of(values: Column) -> Column:
    """Median of an array: the middle value, or the mean of the two middle ones."""
    s = F.array_sort(F.filter(values, lambda x: x.isNotNull()))
    n = F.size(s)
    low, high = F.try_element_at(s, F.floor((n + 1) / 2).cast("int")), F.try_element_at(s, F.floor(n / 2).cast("int") + 1)
    return F.when(n > 0, (low + high) / 2)


def score(chosen: Column, hashes: Column, k: int, prime: int = PRIME, **options) -> Column:
    """Median over the repetitions of the joint size of the chosen lists and a tile's lists (arrays of arrays)."""
    return median_of(F.zip_with(chosen, hashes, lambda a, b: joint(a, b, k, prime, **options)))


def np_merge(a: np.ndarray, b: np.ndarray, k: int, prime: int = PRIME, how: str = "union") -> np.ndarray:
    """Lists on the last axis, padded with ``prime``; the k smallest of both."""
    x = np.sort(np.concatenate(np.broadcast_arrays(a, b), -1), -1)
    if how == "union":
        x[..., 1:][x[..., 1:] == x[..., :-1]] = prime
        x = np.sort(x, -1)
    return x[..., :k]


def np_size(x: np.ndarray, k: int, prime: int = PRIME, small: str = "exact", estimator: str = "k") -> np.ndarray:
    full = x[..., k - 1] < prime
    out = (k if estimator == "k" else k - 1) / ((x[..., k - 1] + 1) / prime)
    return np.where(full, out, (x < prime).sum(-1) if small == "exact" else np.nan)


class Joint:
    """Joint sizes of the chosen set with every tile, kept up to date from pick to pick.

    A hash value of a tile that the chosen list holds already, or that is not below the list's largest, can never again
    change a joint size: the chosen list only gets smaller values.  So values leave for good, and an estimate looks at what
    is left of a tile's list: its m-th value stands at place m plus the number of smaller chosen ones, and the k-th of both
    lists follows without merging them."""

    def __init__(self, held: np.ndarray, first: int, k: int, prime: int, merge: str = "union", small: str = "exact", estimator: str = "k"):
        self.held, self.k, self.prime, self.merge = held, k, prime, merge
        self.small, self.estimator = small, estimator
        self.shape = held.shape[:2]
        self.chosen = held[first].copy()
        if merge == "union":
            self.value = held.reshape(-1)
            self.owner = np.repeat(np.arange(self.shape[0] * self.shape[1]), held.shape[2])
            use = np.flatnonzero(self.value < prime)
            self.value, self.owner = self.value[use], self.owner[use]
            self._drop()

    def _drop(self) -> None:
        rep = self.owner % self.shape[1]
        full = self.chosen[:, -1] < self.prime
        top = np.where(full, self.chosen[:, -1], self.prime)
        use = np.flatnonzero(self.value < top[rep])
        self.value, self.owner, rep = self.value[use], self.owner[use], rep[use]
        # chosen lists of all repetitions as one ascending array, so that one search serves all
        turns = np.arange(self.shape[1]) * (self.prime + 1)
        if self.shape[1] * (self.prime + 1) < 1 << 62:
            line, key = (self.chosen + turns[:, None]).reshape(-1), self.value + turns[rep]
            at = np.searchsorted(line, key)
            self.below = at - rep * self.k
            new = line[np.minimum(at, len(line) - 1)] != key
        else:
            self.below, new = np.zeros(len(rep), np.int64), np.ones(len(rep), bool)
            for r in range(self.shape[1]):
                mine = np.flatnonzero(rep == r)
                at = np.searchsorted(self.chosen[r], self.value[mine])
                self.below[mine] = at
                new[mine] = self.chosen[r][np.minimum(at, self.k - 1)] != self.value[mine]
        self.value, self.owner, self.below = self.value[new], self.owner[new], self.below[new]

    def add(self, i: int) -> int:
        """The chosen set takes tile i; how many values were looked at."""
        self.chosen = np_merge(self.chosen, self.held[i], self.k, self.prime, self.merge)
        if self.merge != "union":
            return int(self.held.size)
        looked = len(self.value)
        self._drop()
        return looked

    def sizes(self) -> np.ndarray:
        """Estimated joint size for each tile and repetition."""
        if self.merge != "union":
            return np_size(np_merge(self.chosen[None], self.held, self.k, self.prime, self.merge), self.k, self.prime, self.small, self.estimator)
        n, k = self.shape[0] * self.shape[1], self.k
        count = np.bincount(self.owner, minlength=n)
        place = np.arange(len(self.owner)) - (np.cumsum(count) - count)[self.owner]
        inside = place + self.below < k
        m = np.bincount(self.owner[inside], minlength=n)
        largest = np.full(n, -1, np.int64)
        last = np.flatnonzero(inside & (place + 1 == m[self.owner]))
        largest[self.owner[last]] = self.value[last]
        rep = np.tile(np.arange(self.shape[1]), self.shape[0])
        have = (self.chosen < self.prime).sum(1)
        own = np.where(m < k, self.chosen[rep, np.maximum(k - m, 1) - 1], -1)
        kth = np.maximum(largest, own)
        total = have[rep] + count
        top = float(k if self.estimator == "k" else k - 1)
        out = np.where(total >= k, top / ((kth + 1) / float(self.prime)), total if self.small == "exact" else np.nan)
        return out.reshape(self.shape)

    def scores(self) -> np.ndarray:
        """Median over the repetitions."""
        each = self.sizes()
        if self.small == "discard" and np.isnan(each).any():
            some = ~np.isnan(each).all(1)
            out = np.full(len(each), np.nan)
            out[some] = np.nanmedian(each[some], 1)
            return out
        return np.median(each, 1)
