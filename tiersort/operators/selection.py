"""Multisequence selection: the keys at wanted ranks, and where they cut sorted runs.

All wanted ranks of all groups advance together. On the driver each rank is a
bracket of two keys with the number of rows up to them. A round draws pivots
from the rows between, counts what is up to each pivot, and narrows the
brackets; rows outside of all brackets are filtered out by the first key column
before they are looked at. When few rows are left they are fetched. In sorted
runs pivots are found by binary search, stretch by stretch. Where each run is
cut is worked out once, at the end.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tiersort.functions.keys import KeySpec
from tiersort.functions.mixing import PRIME
from tiersort.functions.routing import Router, gap_of, kept_share, runs_below
from tiersort.functions.search import Codes, lex_order, lex_search

OPEN = -1  # a bracket's side without a key


class Keys:
    """Keys that were pivots, as arrays that grow."""

    def __init__(self, codes: Codes):
        self.codes = codes
        self.flags = np.zeros(0, np.int64)
        self.values: list[np.ndarray] = [np.zeros(0, {"int": np.int64, "float": np.float64}.get(kind, object)) for kind, *_ in codes.facts]

    def add(self, flags: np.ndarray, values: list[np.ndarray]) -> np.ndarray:
        at = np.arange(len(self.flags), len(self.flags) + len(flags))
        self.flags = np.concatenate([self.flags, flags])
        self.values = [np.concatenate([a, b]) for a, b in zip(self.values, values)]
        return at

    def take(self, which: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
        return self.flags[which], [v[which] for v in self.values]


def _ordered(keys: Keys, pairs: set[tuple[int, int]]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (parent, key) pairs in order, as two arrays."""
    owner, which = np.array([g for g, _ in pairs], np.int64), np.array([i for _, i in pairs], np.int64)
    rows, ways = keys.codes.arrays(*keys.take(which))
    order = lex_order([owner, *rows], [True, *ways])
    return owner[order], which[order]


def _near(rows: DataFrame, key: KeySpec, keys: Keys, brackets: list[list]) -> DataFrame:
    """``rows`` without those that the first key column puts outside of every bracket, if a plain comparison can tell."""
    kind, asc, *_ = keys.codes.facts[0]
    t = rows.schema[key.names[0]].dataType
    ends = {(b[0], b[1]) for b in brackets}
    if not isinstance(t, (T.IntegralType, T.DoubleType, T.FloatType, T.StringType)) or not ends or any(OPEN in e or (keys.flags[list(e)] & 3).any() for e in ends):
        return rows
    spans = sorted((keys.values[0][a], keys.values[0][b]) if asc else (keys.values[0][b], keys.values[0][a]) for a, b in ends)
    if len(spans) > 64:
        spans = [(spans[0][0], max(b for _, b in spans))]
    plain = lambda x: x.item() if hasattr(x, "item") else x
    inside, c = F.lit(False), F.col(key.names[0])
    for a, b in spans:
        inside = inside | ((c >= F.lit(plain(a))) & (c <= F.lit(plain(b))))
    return rows.where(inside)


def select_keys(rows: DataFrame, key: KeySpec, ranks: dict[int, list[int]], sizes: dict[int, int], block: Column, ident: tuple[str, ...], base: list[int] | None = None,
                pos: str | None = None, pivots_per_round: int = 32, seed: int = 1, most_collect: int = 50_000, stats: dict | None = None) -> tuple[Keys, dict[tuple[int, int], int | None]]:
    """Keys, and for each (group, rank) the number of the ``rank``-th smallest of that group (None: rank 0).

    Groups are numbered as in ``sizes`` and own the PEs from ``base`` on;
    ``block`` is a row's PE. ``ident`` names columns that tell equal keys
    apart. With ``pos``, rows of a PE are a sorted run by that column. One
    pivot a round, drawn at random from what remains, is the textbook way;
    more, around a rank's expected place in a sample, save rounds.
    """
    codes = Codes(rows, key, ident)
    keys, base = Keys(codes), base or [0]
    state = {(g, k): [OPEN, OPEN, 0, sizes[g]] for g, ks in ranks.items() for k in ks}
    place = F.pmod(F.xxhash64(*ident, F.lit(seed)), F.lit(PRIME))
    read: list[int] = []

    def answer(w: tuple[int, int]) -> int | None | bool:
        lo, hi, a, b = state[w]
        if w[1] <= a:
            return None if lo == OPEN else lo
        return hi if w[1] == b and hi != OPEN else False

    turn = 0
    while True:
        left = {w: s for w, s in state.items() if answer(w) is False}
        if not left:
            break
        turn += 1
        brackets = {(w[0], s[0], s[1]): s for w, s in left.items()}
        total = sum(s[3] - s[2] for s in brackets.values())
        read.append(total)
        owner, which = _ordered(keys, {(g, e) for g, lo, hi in brackets for e in (lo, hi) if e != OPEN}) if any(OPEN not in (lo, hi) or lo != hi for _, lo, hi in brackets) else (np.zeros(0, np.int64),) * 2
        router = Router(codes, len(codes), owner, *keys.take(which), base)
        # gaps between bounds: how many rows of each bracket are wanted
        everything = total <= most_collect
        share = np.zeros(len(owner) + len(base), np.int64)
        number = {(int(g), int(i)): n for n, (g, i) in enumerate(zip(owner, which))}
        for (g, lo, hi), s in brackets.items():
            gap = g + (number[g, hi] if hi != OPEN else int(np.searchsorted(owner, g, "right")))
            asked = sum(1 for w in left if (w[0], *state[w][:2]) == (g, lo, hi))
            want = 4 if pivots_per_round == 1 else 16 * pivots_per_round * asked
            share[gap] = PRIME if everything else min(PRIME, int(PRIME * (want + 3 * want ** 0.5 + 20) / (s[3] - s[2])) + 1)
        close = _near(rows, key, keys, list(brackets.values()))
        moved = F.pmod(place + turn * 1_000_003, F.lit(PRIME))
        drawn = close.where(moved < int(share.max())).where(kept_share(router, share, block, moved)).select(
            block.alias("_g"), moved.alias("_h"), *codes.named()).toArrow()  # most_collect rows, or some for each rank
        flags, values = codes.read([drawn.column(i) for i in range(2, drawn.num_columns)])
        parent = router.parent(drawn.column(0).to_numpy())
        arrays, ways = codes.arrays(flags, values)
        order = lex_order([parent, *arrays], [True, *ways])
        below = lex_search([parent, *arrays] if router.many else arrays, router.table, router.ways) + parent if len(owner) else parent
        hashes = drawn.column(1).to_numpy()
        pivots: set[tuple[int, int]] = set()
        added = keys.add(flags[order], [v[order] for v in values])
        of_gap: dict[int, np.ndarray] = {int(n): added[below[order] == n] for n in np.unique(below)}
        rank_of = dict(zip(added.tolist(), hashes[order].tolist()))
        for w, (lo, hi, a, b) in left.items():
            g = w[0]
            gap = g + (number[g, hi] if hi != OPEN else int(np.searchsorted(owner, g, "right")))
            some = of_gap.get(gap, np.zeros(0, np.int64))
            if everything:
                at = some[w[1] - a - 1]
                state[w] = [at, at, w[1], w[1]]
            elif len(some) and pivots_per_round == 1:
                pivots.add((g, min(some.tolist(), key=rank_of.get)))
            elif len(some):
                q, s = (w[1] - a) / (b - a), len(some)
                wide = 3 * (s * q * (1 - q)) ** 0.5 + 2
                x, y = max(0, int(q * s - wide)), min(s - 1, int(q * s + wide) + 1)
                spots = np.unique(np.linspace(x, y, min(pivots_per_round, y - x + 1)).astype(int))
                pivots |= {(g, int(some[i])) for i in spots}
        if everything:
            continue
        # rows up to each pivot, counted from the bracket's lower key on
        owner, which = _ordered(keys, pivots | {(g, e) for g, lo, hi in brackets for e in (lo, hi) if e != OPEN})
        if not len(owner):
            continue
        router = Router(codes, len(codes), owner, *keys.take(which), base)
        upto = np.zeros(len(owner), np.int64)
        if pos is None:
            gaps = np.zeros(len(owner) + len(base), np.int64)
            for n, k in close.groupBy(gap_of(router, block).alias("n")).count().collect():  # as many numbers as pivots
                gaps[n] = k
            for g in range(len(base)):
                mine = np.flatnonzero(owner == g)
                upto[mine] = np.cumsum(gaps[mine + g])
        else:
            found = close.select(block.alias("block"), F.col(pos).cast("long").alias("pos"), *codes.named()).mapInArrow(runs_below(router, False), "pe long, bound long, n long")
            for r in found.groupBy("bound").agg(F.sum("n").alias("n")).collect():  # as many numbers as pivots
                upto[r.bound] = r.n
        number = {(int(g), int(i)): n for n, (g, i) in enumerate(zip(owner, which))}
        for w, (lo, hi, a, b) in left.items():
            x = number[w[0], lo] + 1 if lo != OPEN else int(np.searchsorted(owner, w[0]))
            y = number[w[0], hi] if hi != OPEN else int(np.searchsorted(owner, w[0], "right"))
            c = a + upto[x:y] - (upto[x - 1] if lo != OPEN else 0)  # pivots within the bracket, in order
            n = int(np.searchsorted(c, w[1]))
            if n:
                state[w][0], state[w][2] = int(which[x + n - 1]), int(c[n - 1])
            if n < len(c):
                state[w][1], state[w][3] = int(which[x + n]), int(c[n])
    if stats is not None:
        stats |= {"rounds": turn, "rows_read": read, "ranks": len(state)}
    return keys, {w: answer(w) for w in state}


def cut_positions(runs: DataFrame, key: KeySpec, keys: Keys, cuts: dict[tuple[int, int], int | None], block: Column, pos: str, base: list[int]) -> dict[tuple[int, int], dict[int, int]]:
    """{(group, rank): {run: rows of it up to the cut}}, for runs that have rows; one number for each run and cut."""
    owner, which = _ordered(keys, {(w[0], i) for w, i in cuts.items() if i is not None}) if any(i is not None for i in cuts.values()) else (np.zeros(0, np.int64),) * 2
    out: dict[tuple[int, int], dict[int, int]] = {w: {} for w in cuts}
    if not len(owner):
        return out
    router = Router(keys.codes, len(keys.codes), owner, *keys.take(which), base)
    found = runs.select(block.alias("block"), F.col(pos).cast("long").alias("pos"), *keys.codes.named()).mapInArrow(runs_below(router, True), "pe long, bound long, n long")
    number: dict[tuple[int, int], list[tuple[int, int]]] = {}
    for w, i in cuts.items():
        if i is not None:
            number.setdefault((w[0], i), []).append(w)
    for r in found.groupBy("pe", "bound").agg(F.sum("n").alias("n")).collect():
        for w in number[int(owner[r.bound]), int(which[r.bound])]:
            out[w][r.pe] = r.n
    return out


def select_splits(runs: DataFrame, key: KeySpec, ranks: dict[int, list[int]], pe: str = "_ms_pe", pos: str = "_ms_pos", grp: str = "_ms_grp", lengths: dict[tuple[int, int], int] | None = None,
                  pivots_per_round: int = 32, seed: int = 1, stats: dict | None = None, most_collect: int = 50_000) -> dict[tuple[int, int], dict[int, int]]:
    """{(group, rank): {pe: position}}: the first ``position`` elements of each run are the group's ``rank`` smallest.

    ``runs`` has sorted runs with positions from 0. Equal keys are told apart
    by their origin (run, then position), so keys may repeat.
    """
    if lengths is None:
        lengths = {(r[0], r[1]): r[2] for r in runs.groupBy(grp, pe).count().collect()}  # a row for each run
    names = sorted({g for g, _ in lengths} | set(ranks))
    number = {g: i for i, g in enumerate(names)}
    sizes = {i: sum(n for (h, _), n in lengths.items() if h == g) for g, i in number.items()}
    # groups may have any runs: each gets a stretch of numbers of its own
    block, base = F.col(grp).cast("long") * (1 << 32) + F.col(pe), [g << 32 for g in names]
    ident = (pe, pos)
    asked = {number[g]: sorted(set(ks)) for g, ks in ranks.items()}
    keys, cuts = select_keys(runs, key, asked, sizes, block, ident, base, pos, pivots_per_round, seed, most_collect, stats)
    found = cut_positions(runs, key, keys, cuts, block, pos, base)
    out: dict[tuple[int, int], dict[int, int]] = {}
    for g, ks in ranks.items():
        for k in ks:
            got = found[number[g], k]
            out[g, k] = {e: (n if k >= sizes[number[g]] else int(got.get((g << 32) + e, 0))) for (h, e), n in lengths.items() if h == g}
    return out


def at_ranks(rows: DataFrame, key: KeySpec, ranks: list[int], ident: tuple[str, ...], n: int | None = None, seed: int = 1, stats: dict | None = None) -> DataFrame:
    """Rows (at, key columns): the elements of the wanted ranks (from 0) of an unsorted table, without sorting it."""
    n = rows.count() if n is None else n
    wanted = sorted({k for k in ranks if 0 <= k < n})
    keys, cuts = select_keys(rows, key, {0: [k + 1 for k in wanted]}, {0: n}, F.lit(0).cast("long"), ident, seed=seed, stats=stats)
    if not wanted:
        return rows.select(F.lit(0).cast("long").alias("at"), *key.names).limit(0)
    # the rows of these keys, found again by their origin
    depth = len(keys.codes) - len(ident)
    which = np.array([cuts[0, k + 1] for k in wanted])
    names = [f"_ms_o{i}" for i in range(len(ident))]
    table = rows.sparkSession.createDataFrame([(k, *(int(keys.values[depth + i][w]) for i in range(len(ident)))) for k, w in zip(wanted, which)], ["at", *names])
    same = F.lit(True)
    for c, o in zip(ident, names):
        same = same & (F.col(c) == F.col(o))
    return rows.join(F.broadcast(table), same).select("at", *key.names)  # a row for each rank
