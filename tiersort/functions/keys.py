"""Sort keys: columns with direction and place of nulls, comparisons, ties."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


@dataclass(frozen=True)
class KeySpec:
    """An order of rows: ``cols`` with ``asc`` and ``nulls_first`` for each, then ``ties``.

    With ``ties`` naming columns that are unique together, keys are unique and
    loads can be balanced whatever the repetition of the key; without, equal
    keys stay together.
    """

    cols: tuple[str, ...]
    asc: tuple[bool, ...] = ()
    nulls_first: tuple[bool, ...] = ()
    ties: tuple[str, ...] = ()
    _all: tuple[tuple[str, bool, bool], ...] = field(init=False, default=())

    def __post_init__(self) -> None:
        asc = self.asc or (True,) * len(self.cols)
        first = self.nulls_first or asc  # Spark's own default
        extra = tuple((c, True, True) for c in self.ties if c not in self.cols)
        object.__setattr__(self, "_all", tuple(zip(self.cols, asc, first)) + extra)

    @property
    def names(self) -> list[str]:
        return [c for c, _, _ in self._all]

    def without_ties(self) -> KeySpec:
        return KeySpec(self.cols, self.asc, self.nulls_first)

    def resolve(self, df: DataFrame) -> KeySpec:
        """Raises a clear error for missing columns and types without an order."""
        def orderable(t: T.DataType) -> bool:
            if isinstance(t, (T.MapType, T.VariantType)):
                return False
            if isinstance(t, T.ArrayType):
                return orderable(t.elementType)
            if isinstance(t, T.StructType):
                return all(orderable(f.dataType) for f in t)
            return True
        kinds = {f.name: f.dataType for f in df.schema}
        for c in self.names:
            if c not in kinds:
                raise ValueError(f"no column {c}")
            if not orderable(kinds[c]):
                raise TypeError(f"column {c} of type {kinds[c].simpleString()} has no order")
        return self

    def order(self) -> list[Column]:
        out = []
        for c, asc, first in self._all:
            x = F.col(c)
            out.append((x.asc_nulls_first() if first else x.asc_nulls_last()) if asc else (x.desc_nulls_first() if first else x.desc_nulls_last()))
        return out

    def steady(self, df: DataFrame) -> list[Column]:
        """``order``, with equal keys in an order of the other columns, so that a task that runs again numbers its rows as before."""
        rest = [F.col(f.name) for f in df.schema if f.name not in self.names and "map<" not in f.dataType.simpleString() and "variant" not in f.dataType.simpleString()]
        return [*self.order(), F.xxhash64(*rest)] if rest else self.order()

    def struct(self) -> Column:
        return F.struct(*[F.col(c).alias(f"k{i}") for i, c in enumerate(self.names)])

    def above(self, other: Column) -> Column:
        """Whether a row's key is strictly after the key struct ``other``."""
        out = F.lit(False)
        for i in range(len(self._all) - 1, -1, -1):
            c, asc, first = self._all[i]
            mine, its = F.col(c), other[f"k{i}"]
            beyond = (mine > its) if asc else (mine < its)
            null_case = (mine.isNotNull() & its.isNull()) if first else (mine.isNull() & its.isNotNull())
            strict = F.coalesce(beyond, F.lit(False)) | null_case
            out = strict | (mine.eqNullSafe(its) & out) if i < len(self._all) - 1 else strict
        return out

    def equal(self, other: Column) -> Column:
        out = F.lit(True)
        for i, c in enumerate(self.names):
            out = out & F.col(c).eqNullSafe(other[f"k{i}"])
        return out


def key(*cols: str, desc: tuple[str, ...] = (), nulls_last: tuple[str, ...] = (), nulls_first: tuple[str, ...] = (), ties: tuple[str, ...] = ()) -> KeySpec:
    """Shorthand: columns in order, those in ``desc`` descending."""
    asc = tuple(c not in desc for c in cols)
    first = tuple((c in nulls_first) or (c not in nulls_last and a) for c, a in zip(cols, asc))
    return KeySpec(tuple(cols), asc, first, tuple(ties))
