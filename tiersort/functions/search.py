"""Keys as arrays: encoding of key columns, searching and ordering by several of them.

Workers get the functions of this module by value, so executors need not have
the package.
"""

from __future__ import annotations

import sys
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tiersort.functions.keys import KeySpec

cloudpickle.register_pickle_by_value(sys.modules[__name__])


@dataclass(frozen=True)
class Leaf:
    """One comparable column: ``value`` without nulls and NaN, flagged by bits of the key's flags."""

    value: Column
    kind: str  # int, float, object, list
    asc: bool
    nulls_first: bool
    null: Column
    nan: Column | None


def _ntz_micros(c: Column) -> Column:
    """Microseconds since 1970 of a time without zone, whatever the session's zone."""
    day = F.unix_date(c.cast("date")).cast("long") * 86_400_000_000
    return day + (F.hour(c).cast("long") * 3600 + F.minute(c).cast("long") * 60) * 1_000_000 + (F.extract(F.lit("SECOND"), c) * 1_000_000).cast("long")


def _leaves(c: Column, t: T.DataType, asc: bool, nulls_first: bool, above: Column | None = None) -> list[Leaf]:
    null = c.isNull() if above is None else above | c.isNull()

    def one(value: Column, kind: str, empty, nan: Column | None = None) -> list[Leaf]:
        return [Leaf(F.coalesce(value, F.lit(empty)), kind, asc, nulls_first, null, nan)]

    if isinstance(t, T.StructType):  # nulls of fields are smallest, as Spark compares them
        first = [Leaf(F.lit(0).cast("long"), "int", asc, nulls_first, null, None)]
        return first + [leaf for f in t for leaf in _leaves(c[f.name], f.dataType, asc, asc, null)]
    if isinstance(t, (T.FloatType, T.DoubleType)):
        return one(F.when(F.isnan(c), F.lit(0.0)).otherwise(c.cast("double")), "float", 0.0, F.coalesce(F.isnan(c), F.lit(False)))
    if isinstance(t, (T.BooleanType, T.IntegralType)):
        return one(c.cast("long"), "int", 0)
    if isinstance(t, T.DateType):
        return one(F.unix_date(c).cast("long"), "int", 0)
    if isinstance(t, T.TimestampType):
        return one(F.unix_micros(c), "int", 0)
    if isinstance(t, T.TimestampNTZType):
        return one(_ntz_micros(c), "int", 0)
    if isinstance(t, T.DecimalType):
        if t.precision <= 18:
            return one((c * F.lit(10 ** t.scale)).cast("long") if t.scale else c.cast("long"), "int", 0)
        return [Leaf(F.coalesce(c, F.lit(0).cast(t)), "object", asc, nulls_first, null, None)]
    if isinstance(t, T.BinaryType):
        return [Leaf(F.coalesce(c, F.lit(b"")), "object", asc, nulls_first, null, None)]
    if isinstance(t, T.StringType):
        return one(c, "object", "")
    if isinstance(t, T.ArrayType):
        return [Leaf(F.coalesce(c, F.array().cast(t)), "list", asc, nulls_first, null, None)]
    if isinstance(t, T.YearMonthIntervalType):
        return one((F.extract(F.lit("YEAR"), c) * 12 + F.extract(F.lit("MONTH"), c)).cast("long"), "int", 0)
    if isinstance(t, T.DayTimeIntervalType):
        part = lambda unit: F.extract(F.lit(unit), c)
        return one(((part("DAY").cast("long") * 24 + part("HOUR")) * 60 + part("MINUTE")) * 60_000_000 + (part("SECOND") * 1_000_000).cast("long"), "int", 0)
    raise TypeError(f"{t.simpleString()} can't be split by")


def _listed(x) -> tuple:
    """An array's value as something that Python compares as Spark does: nulls first, NaN last."""
    return tuple((0,) if v is None else (1, v != v, 0 if v != v else v) if not isinstance(v, (list, np.ndarray)) else (1, False, _listed(v)) for v in x)


class Codes:
    """A key's columns as Arrow columns (``columns``) and, in a worker, as arrays (``arrays``)."""

    def __init__(self, df: DataFrame, key: KeySpec, origin: tuple[str, ...] = ()):
        kinds = {f.name: f.dataType for f in df.schema}
        leaves = [leaf for c, asc, first in key._all for leaf in _leaves(F.col(c), kinds[c], asc, first)]
        leaves += [Leaf(F.col(c).cast("long"), "int", True, True, F.lit(False), None) for c in origin]
        flags = F.lit(0).cast("long")
        for i, leaf in enumerate(leaves):
            flags = flags.bitwiseOR(F.when(leaf.null, F.lit(1 << 2 * i).cast("long")).otherwise(F.lit(0).cast("long")))
            if leaf.nan is not None:
                flags = flags.bitwiseOR(F.when(leaf.nan, F.lit(2 << 2 * i).cast("long")).otherwise(F.lit(0).cast("long")))
        if len(leaves) > 31:
            raise ValueError("at most 31 key columns")
        self.flags, self.values = flags, [leaf.value for leaf in leaves]
        self.facts = [(leaf.kind, leaf.asc, leaf.nulls_first, leaf.nan is not None) for leaf in leaves]

    def __getstate__(self) -> dict:
        return {"facts": self.facts}  # columns stay on the driver

    def __len__(self) -> int:
        return len(self.facts)

    def columns(self, depth: int | None = None) -> list[Column]:
        """Flags, then the values of the first ``depth`` leaves."""
        return [self.flags, *self.values[:depth]]

    def named(self, depth: int | None = None) -> list[Column]:
        return [c.alias(f"_c{i}") for i, c in enumerate(self.columns(depth))]

    def read(self, columns: list) -> tuple[np.ndarray, list[np.ndarray]]:
        """Flags and values of Arrow or pandas columns given in the order of ``columns``."""
        out = []
        for (kind, *_), c in zip(self.facts, columns[1:]):
            if kind in ("int", "float"):
                out.append(c.to_numpy(zero_copy_only=False) if isinstance(c, (pa.Array, pa.ChunkedArray)) else c.to_numpy())
            else:
                x = np.empty(len(c), object)
                items = c.to_pylist() if isinstance(c, (pa.Array, pa.ChunkedArray)) else c.tolist()
                x[:] = [_listed(v) for v in items] if kind == "list" else items
                out.append(x)
        flags = columns[0]
        return (flags.to_numpy(zero_copy_only=False) if isinstance(flags, (pa.Array, pa.ChunkedArray)) else flags.to_numpy()), out

    def arrays(self, flags: np.ndarray, values: list[np.ndarray], depth: int | None = None) -> tuple[list[np.ndarray], list[bool]]:
        """Arrays to compare one after the other, and whether each ascends; for each leaf that of nulls, of NaN, of values."""
        out, ways = [], []
        for i, (v, (_, asc, first, nan)) in enumerate(zip(values[:depth], self.facts)):
            null = (flags >> (2 * i)) & 1
            out.append(1 - null if first else null)
            ways.append(True)
            if nan:
                out.append((flags >> (2 * i + 1)) & 1)
                ways.append(asc)
            out.append(v)
            ways.append(asc)
        return out, ways


def without_constant(rows: list[np.ndarray], table: list[np.ndarray], ways: list[bool]) -> tuple[list, list, list]:
    """Leaves out flag columns that say the same on both sides."""
    keep = []
    for i, (a, b) in enumerate(zip(rows, table)):
        plain = a.dtype.kind == "i" and len(a) and len(b) and i + 1 < len(rows)
        keep.append(not (plain and b[0] in (0, 1) and (b == b[0]).all() and (a == b[0]).all()))
    some = [i for i, k in enumerate(keep) if k] or [len(rows) - 1]
    return [rows[i] for i in some], [table[i] for i in some], [ways[i] for i in some]


def lex_search(rows: list[np.ndarray], table: list[np.ndarray], ways: list[bool], right: bool = False) -> np.ndarray:
    """Number of table entries strictly before each row (with ``right``: before or equal); the table is in order.

    Rows equal to entries in one column go on with the next column among
    these entries, all rows of such a run at once.
    """
    out = np.zeros(len(rows[0]), np.int64)
    if not len(table[0]) or not len(out):
        return out
    rows, table, ways = without_constant(rows, table, ways)

    def go(some: np.ndarray | None, low: int, high: int, depth: int) -> None:
        part = table[depth][low:high]
        v = rows[depth] if some is None else rows[depth][some]
        if ways[depth]:
            a, b = np.searchsorted(part, v, "left"), np.searchsorted(part, v, "right")
        else:
            a, b = len(part) - np.searchsorted(part[::-1], v, "right"), len(part) - np.searchsorted(part[::-1], v, "left")
        last = depth + 1 == len(table)
        found = low + (b if last and right else a)
        if some is None:
            out[:] = found
        else:
            out[some] = found
        if last:
            return
        tied = np.flatnonzero(b > a)
        if not len(tied):
            return
        order = np.argsort(a[tied], kind="stable")
        tied = tied[order]
        at = a[tied]
        edge = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1], [True]]))
        for x, y in zip(edge, edge[1:]):
            mine = tied[x:y]
            go(mine if some is None else some[mine], low + int(at[x]), low + int(b[mine[0]]), depth + 1)

    go(None, 0, len(table[0]), 0)
    return out


def lex_order(rows: list[np.ndarray], ways: list[bool]) -> np.ndarray:
    """Row numbers in order."""
    codes = []
    for x, asc in zip(rows, ways):
        code = np.unique(x, return_inverse=True)[1].reshape(-1)
        codes.append(code if asc else -code)
    return np.lexsort(codes[::-1]) if codes else np.zeros(0, np.int64)


def same_as_next(rows: list[np.ndarray]) -> np.ndarray:
    """Number of leading columns in which each row equals the next one."""
    n = max(0, len(rows[0]) - 1)
    out, live = np.zeros(n, np.int64), np.ones(n, bool)
    for x in rows:
        live = live & (x[1:] == x[:-1])
        out += live
    return out


def before_next(rows: list[np.ndarray], ways: list[bool]) -> np.ndarray:
    """Whether each row is not after the next one."""
    n = max(0, len(rows[0]) - 1)
    good, open_ = np.ones(n, bool), np.ones(n, bool)
    for x, asc in zip(rows, ways):
        a, b = (x[:-1], x[1:]) if asc else (x[1:], x[:-1])
        good &= ~(open_ & (b < a))
        open_ &= a == b
    return good
