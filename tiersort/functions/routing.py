"""What workers do with rows: find their bucket, their target, and count sorted runs below pivots.

Functions of this module go to the workers by value.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import Column
from pyspark.sql import functions as F

from tiersort.functions.search import Codes, lex_search

cloudpickle.register_pickle_by_value(sys.modules[__name__])
RUN = 1 << 40  # more rows than a run has


class Router:
    """Bounds of all PE groups (parents): ``owner`` numbers each bound's parent, flags and values name it, in order.

    Parents own the PEs from ``base`` on; a block is one of ``c`` parts of a PE's rows.
    """

    def __init__(self, codes: Codes, depth: int, owner: np.ndarray, flags: np.ndarray, values: list[np.ndarray], base: list[int], c: int = 1):
        self.codes, self.depth, self.c, self.base = codes, depth, c, np.array(base, np.int64)
        table, ways = codes.arrays(flags, values, depth)
        self.many = len(base) > 1
        self.owner = owner
        self.table, self.ways = ([owner, *table], [True, *ways]) if self.many else (table, ways)
        self.first = np.searchsorted(owner, np.arange(len(base)))

    def parent(self, block: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.base, block // self.c, "right") - 1

    def bounds_below(self, block: np.ndarray, columns: list) -> tuple[np.ndarray, np.ndarray]:
        """Each row's parent, and how many of its bounds are strictly before the row."""
        g = self.parent(block)
        rows, _ = self.codes.arrays(*self.codes.read(columns), self.depth)
        at = lex_search([g, *rows] if self.many else rows, self.table, self.ways)
        return g, at - self.first[g]


def bucket_of(router: Router, buckets: int, block: Column) -> Column:
    """Number of the row's bucket, counted through over the parents (``buckets`` for each)."""
    def run(block: pd.Series, *columns: pd.Series) -> pd.Series:
        g, at = router.bounds_below(block.to_numpy(), list(columns))
        return pd.Series(g * buckets + at)

    return F.pandas_udf(run, "long")(block, *router.codes.columns(router.depth))


def part_of(router: Router, buckets: int, part: np.ndarray, block: Column) -> Column:
    """Number of the row's part within its parent; ``part`` has one for each bucket."""
    def run(block: pd.Series, *columns: pd.Series) -> pd.Series:
        g, at = router.bounds_below(block.to_numpy(), list(columns))
        return pd.Series(part[g * buckets + at])

    return F.pandas_udf(run, "int")(block, *router.codes.columns(router.depth))


def target_of(router: Router, buckets: int, part: np.ndarray, targets: np.ndarray, block: Column) -> Column:
    """PE that the row goes to: ``targets`` has one for each block and part."""
    def run(block: pd.Series, *columns: pd.Series) -> pd.Series:
        b = block.to_numpy()
        g, at = router.bounds_below(b, list(columns))
        return pd.Series(targets[b, part[g * buckets + at]])

    return F.pandas_udf(run, "int")(block, *router.codes.columns(router.depth))


def run_target(names: np.ndarray, starts: np.ndarray, parent: np.ndarray, local: np.ndarray, dealings: list, pe: Column, pos: Column) -> Column:
    """PE that a run's row goes to: ``starts`` has, for each run, where its piece for each part begins.

    ``names`` are the runs' numbers in order, ``parent`` and ``local`` their
    PE group and number in it, ``dealings`` the delivery of each group.
    """
    r = starts.shape[1]
    flat = (np.arange(len(names))[:, None] * RUN + starts).reshape(-1)

    def run(pe: pd.Series, pos: pd.Series) -> pd.Series:
        e, x = np.searchsorted(names, pe.to_numpy()), pos.to_numpy()
        at = np.searchsorted(flat, e * RUN + x, "right") - 1  # of empty pieces at one place the last one is meant
        j = at - e * r
        out, g = np.empty(len(e), np.int64), parent[e]
        for k in np.unique(g):
            mine = np.flatnonzero(g == k)
            out[mine] = dealings[k].at(local[e[mine]], j[mine], x[mine] - starts[e[mine], j[mine]])
        return pd.Series(out)

    return F.pandas_udf(run, "int")(pe, pos)


def kept_share(router: Router, share: np.ndarray, block: Column, place: Column) -> Column:
    """Whether a row lies between bounds of which a share is wanted, and its place (below 2^31) is within it.

    ``share`` has the bound of places for each gap: those of the first parent, then the next.
    """
    offset = router.first + np.arange(len(router.base))

    def run(block: pd.Series, place: pd.Series, *columns: pd.Series) -> pd.Series:
        g, at = router.bounds_below(block.to_numpy(), list(columns))
        return pd.Series(place.to_numpy() < share[offset[g] + at])

    return F.pandas_udf(run, "boolean")(block, place, *router.codes.columns(router.depth))


def gap_of(router: Router, block: Column) -> Column:
    """Number of the gap between bounds that a row lies in, counted through over the parents."""
    offset = router.first + np.arange(len(router.base))

    def run(block: pd.Series, *columns: pd.Series) -> pd.Series:
        g, at = router.bounds_below(block.to_numpy(), list(columns))
        return pd.Series(offset[g] + at)

    return F.pandas_udf(run, "long")(block, *router.codes.columns(router.depth))


def reached(codes: Codes, firsts: tuple, lasts: tuple, begin: list[Column], end: list[Column]) -> Column:
    """Struct (a, b): numbers of the first and the last PE whose keys can lie between ``begin`` and ``end`` (codes of both, in the order's direction).

    ``firsts`` and ``lasts`` are the PEs' first and last keys (flags, values).
    The last number is below the first one if there is no such PE.
    """
    first, ways = codes.arrays(*firsts)
    last, _ = codes.arrays(*lasts)
    width = len(begin)

    def run(*columns: pd.Series) -> pd.DataFrame:
        a, _ = codes.arrays(*codes.read(list(columns[:width])))
        b, _ = codes.arrays(*codes.read(list(columns[width:])))
        return pd.DataFrame({"a": lex_search(a, last, ways), "b": lex_search(b, first, ways, right=True) - 1})

    return F.pandas_udf(run, "a int, b int")(*begin, *end)


def runs_below(router: Router, by_run: bool):
    """Function for ``mapInArrow`` over rows (block, pos, codes) of sorted runs: rows (pe, bound, n), rows up to each bound.

    Every stretch of a run in a batch is in order, so each bound is found in
    it by binary search.
    """
    where = [np.flatnonzero(router.owner == g) for g in range(len(router.base))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for b in batches:
            if not b.num_rows:
                continue
            block, pos = b.column(0).to_numpy(zero_copy_only=False), b.column(1).to_numpy(zero_copy_only=False)
            order = np.lexsort((pos, block)) if len(block) > 1 and ((block[1:] != block[:-1]) | (pos[1:] < pos[:-1])).any() else np.arange(len(block))
            block = block[order]
            rows, ways = router.codes.arrays(*router.codes.read(b.columns[2:]), router.depth)
            rows = [x[order] for x in rows]
            edge = np.flatnonzero(np.concatenate([[True], block[1:] != block[:-1], [True]]))
            for x, y in zip(edge, edge[1:]):
                g = int(router.parent(block[x:x + 1])[0])
                mine = where[g]
                bounds = [t[mine] for t in (router.table[1:] if router.many else router.table)]
                n = lex_search(bounds, [v[x:y] for v in rows], ways, right=True)
                name = int(block[x] // router.c) if by_run else g
                total[name] = total.get(name, 0) + n
        for name, n in total.items():
            g = int(router.parent(np.array([name * router.c]))[0]) if by_run else name
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), name), pa.int64()), pa.array(where[g], pa.int64()), pa.array(n, pa.int64())], names=["pe", "bound", "n"])

    return run
