"""Level plans: into how many groups each level splits, and PE ranges of groups."""

from __future__ import annotations

import math


def per_level_eps(eps: float, k: int) -> float:
    """Imbalance allowed on each of k levels so that the whole keeps within 1 + eps."""
    return (1 + eps) ** (1 / k) - 1


def suggest_ab(eps: float, r: int) -> tuple[float, int]:
    """Oversampling and overpartitioning for an imbalance of eps: b buckets per group of mean eps/2, enough samples for each."""
    b = max(1, math.ceil(2 / eps))
    return max(1.0, max(math.log(max(2, r)), 1 / eps) / b), b


def oversampling(n: int) -> float:
    """Samples for each bucket, growing with the logarithm of the input."""
    return max(1.0, 1.6 * math.log10(max(10, n)))


def plan_levels(p: int, k: int | str, how: str = "root", node: int = 16, shape: list[int] | None = None, rows: int | None = None) -> list[int]:
    """Numbers of groups by level, whose product is p.

    ``root``: about the k-th root of p on each level. ``node``: the last level
    works inside a node, the levels above share the bits of p / node, the first
    getting the odd one. ``topology``: ``shape`` itself (islands, nodes, cores).
    ``k='log'`` halves every time; ``k='auto'`` takes the cheapest of 1 to 3 by
    block start-ups against moved rows.
    """
    if p < 1:
        raise ValueError("p must be positive")
    if how == "topology":
        if not shape or math.prod(shape) != p:
            raise ValueError("shape must multiply to p")
        return [x for x in shape if x > 1] or [1]
    if k == "log":
        return [2] * (p.bit_length() - 1) if p & (p - 1) == 0 else factors(p)
    if k == "auto":
        n = rows or p * 1_000_000
        return min((plan_levels(p, j, how, node) for j in (1, 2, 3)), key=lambda plan: sum(1e5 * r + n / p for r in plan))
    if k == 1 or p == 1:
        return [p]
    if how == "node" and p % node == 0 and p > node:
        if k == 2:
            return [p // node, node]
        bits = (p // node).bit_length() - 1
        if k == 3 and p // node == 1 << bits and bits > 1:
            return [1 << -(-bits // 2), 1 << bits // 2, node]
    out, left = [], p
    for level in range(k, 1, -1):
        want = left ** (1 / level)
        r = min((d for d in range(1, left + 1) if left % d == 0), key=lambda d: (abs(math.log(d) - math.log(want)), -d))
        out.append(r)
        left //= r
    return [r for r in [*out, left] if r > 1] or [1]


def factors(p: int) -> list[int]:
    out, d = [], 2
    while p > 1:
        while p % d == 0:
            out.append(d)
            p //= d
        d += 1
    return out or [1]


def group_range(base: int, size: int, r: int, j: int) -> tuple[int, int]:
    """First PE and number of PEs of the j-th of r groups of the PEs [base, base + size)."""
    a, b = j * size // r, (j + 1) * size // r
    return base + a, b - a
