"""Integer mixing that Spark, Python and SQL compute alike, and curve keys."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = 2147483647
FACTOR = 1103515245  # large, so that small numbers are spread too; products stay below 2^62
SMALL_FACTOR = 48271


def h(x: Column) -> Column:
    """Pseudo-random place below PRIME of a non-negative integer below it."""
    return ((x.cast("long") + 1) * FACTOR) % PRIME


def h_of(x: int) -> int:
    return (x + 1) * FACTOR % PRIME


def mix_pair(pe: Column, grp: Column, seed: int) -> Column:
    """Order of PEs in a group's permutation (ties by pe)."""
    return (pe.cast("long") * 7919 + grp.cast("long") * 104729 + seed) * SMALL_FACTOR % PRIME


def random64(x: Column, seed: int = 0) -> Column:
    """Long keys spread over all of 64 bits."""
    return F.xxhash64(x, F.lit(seed))


def morton_key(cells: list[Column], bits: int) -> Column:
    """Interleaved bits of cell numbers, the first cell's bit highest in each level."""
    out = F.lit(0).cast("long")
    for b in range(bits):
        for i, c in enumerate(cells):
            at = b * len(cells) + len(cells) - 1 - i
            out = out.bitwiseOR(F.shiftleft(F.shiftright(c.cast("long"), b).bitwiseAND(F.lit(1).cast("long")), at))
    return out


def quantised(x: Column, low: float, high: float, bits: int) -> Column:
    top = (1 << bits) - 1
    return F.greatest(F.lit(0), F.least(F.lit(top), F.floor((x - low) / (high - low) * (top + 1)))).cast("int")
