"""Delivery of pieces as arrays: the table of piece sizes on the driver, places looked up in the workers.

The same methods as ``operators.delivery`` has for tables of any size; here the
result is not a list of slices but a function from a place in a piece to its
target. Workers get this module's functions by value.
"""

from __future__ import annotations

import sys

import numpy as np
from pyspark import cloudpickle

from tiersort.functions.mixing import PRIME, SMALL_FACTOR

cloudpickle.register_pickle_by_value(sys.modules[__name__])


class Dealing:
    """Delivery of one PE group's pieces: ``sizes`` has a row for each source and a column for each destination group.

    Destination group j owns the PEs [base[j], base[j] + q[j]); ``names`` are
    the sources' PE numbers.
    """

    def __init__(self, sizes: np.ndarray, base: list[int], q: list[int], method: str = "two_phase", capacity: str = "even", seed: int = 1, names: np.ndarray | None = None):
        s, r = sizes.shape
        self.method, self.sizes = method, sizes
        self.base, self.q = np.array(base, np.int64), np.array(q, np.int64)
        names = np.arange(s) if names is None else np.asarray(names, np.int64)
        self.total = sizes.sum(0)
        each = -(-self.total // self.q)
        self.cap = np.full(r, each.max(initial=0)) if capacity == "bound" or method == "two_phase" else each
        self.bound = capacity == "bound"
        if method in ("prefix", "permuted"):
            self.start = np.zeros((s, r), np.int64)
            for j in range(r):
                order = np.arange(s) if method == "prefix" else np.lexsort((names, _mixed(names, self.base[j], seed)))
                self.start[order, j] = np.cumsum(sizes[order, j]) - sizes[order, j]
        elif method == "chunked":
            self.chunk = np.maximum(1, self.cap // (2 * self.q))
            self.first, self.places = np.zeros((s, r), np.int64), []
            for j in range(r):
                n = -(-sizes[:, j] // self.chunk[j])
                self.first[:, j] = np.cumsum(n) - n
                src = np.repeat(np.arange(s), n)
                c = np.arange(len(src)) - self.first[src, j]
                held = np.minimum(self.chunk[j], sizes[src, j] - c * self.chunk[j])
                order = np.lexsort((c, names[src], _mixed(names[src] * 4096 + c, self.base[j], seed)))
                start = np.empty(len(src), np.int64)
                start[order] = np.cumsum(held[order]) - held[order]
                self.places.append(start)
        elif method == "two_phase":
            n = int(self.total.sum())
            small = (sizes > 0) & (sizes * 2 * s * r <= n)
            number = np.cumsum(small, 0) - small
            self.whole = np.where(small, np.minimum(self.q - 1, number * self.q // max(1, s)), -1)
            large = np.where(small, 0, sizes)
            self.ahead = np.cumsum(large, 0) - large
            self.room = []
            for j in range(r):
                given = np.bincount(self.whole[small[:, j], j], weights=sizes[small[:, j], j], minlength=int(self.q[j])).astype(np.int64)
                self.room.append(np.cumsum(self.cap[j] - given))
        else:
            raise ValueError(method)

    def at(self, src: np.ndarray, grp: np.ndarray, x: np.ndarray) -> np.ndarray:
        """Target PE of place ``x`` in the piece of source number ``src`` for group number ``grp``."""
        q = self.q[grp]
        if self.method in ("prefix", "permuted", "chunked"):
            if self.method == "chunked":
                place = np.empty(len(src), np.int64)
                for j in np.unique(grp):
                    k = np.flatnonzero(grp == j)
                    place[k] = self.places[j][self.first[src[k], j] + x[k] // self.chunk[j]] + x[k] % self.chunk[j]
            else:
                place = self.start[src, grp] + x
            t = place // np.maximum(1, self.cap[grp]) if self.bound else place * q // np.maximum(1, self.total[grp])
            return self.base[grp] + np.minimum(t, q - 1)
        t = self.whole[src, grp].copy()
        for j in np.unique(grp):
            k = np.flatnonzero((t < 0) & (grp == j))
            t[k] = np.searchsorted(self.room[j], self.ahead[src[k], j] + x[k], "right")
        return self.base[grp] + np.minimum(t, q - 1)


def _mixed(pe: np.ndarray, grp: int, seed: int) -> np.ndarray:
    return (pe * 7919 + int(grp) * 104729 + seed) * SMALL_FACTOR % PRIME


def traffic(src: np.ndarray, target: np.ndarray, words: np.ndarray) -> dict[str, float]:
    """Messages and words, most and mean, of a PE; what stays on its PE is no message."""
    moved = (words > 0) & (src != target)
    pair, inv = np.unique(src[moved] * (1 << 32) + target[moved], return_inverse=True)
    sent, got = pair >> 32, pair & 0xFFFFFFFF
    load = np.bincount(inv.reshape(-1), weights=words[moved], minlength=len(pair)) if len(pair) else np.zeros(0)

    def side(of: np.ndarray) -> tuple[float, float, float]:
        if not len(of):
            return 0.0, 0.0, 0.0
        names, at, n = np.unique(of, return_inverse=True, return_counts=True)
        return float(n.max()), float(n.mean()), float(np.bincount(at.reshape(-1), weights=load).max())
    a, b = side(sent), side(got)
    return {"max_sent": a[0], "mean_sent": a[1], "max_recv": b[0], "mean_recv": b[1], "bottleneck": max(a[2], b[2]), "words": float(load.sum())}
