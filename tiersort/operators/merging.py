"""Merging the runs a PE has received, over Arrow batches."""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from tiersort.functions.keys import KeySpec
from tiersort.functions.search import Codes, before_next, lex_order

cloudpickle.register_pickle_by_value(sys.modules[__name__])


def merged_order(rows: list[np.ndarray], ways: list[bool], stretches: list[np.ndarray], fan_in: int = 64) -> tuple[np.ndarray, int]:
    """Row numbers in order, from sorted stretches of row numbers, and the number of passes.

    At most ``fan_in`` stretches are merged at once. A merge puts them one
    behind the other and runs a stable run-adaptive sort over the first column
    that differs, which finds the stretches and merges them by comparisons
    from their ends; rows equal there are settled by the other columns.
    """
    passes = 0
    while len(stretches) > 1:
        stretches = [_merge(rows, ways, stretches[i:i + fan_in]) for i in range(0, len(stretches), fan_in)]
        passes += 1
    return stretches[0] if stretches else np.zeros(0, np.int64), passes


def _merge(rows: list[np.ndarray], ways: list[bool], stretches: list[np.ndarray]) -> np.ndarray:
    some = np.concatenate(stretches)
    if len(stretches) == 1:
        return some

    def sort(which: np.ndarray, depth: int) -> np.ndarray:
        while depth < len(rows) and len(which) and (rows[depth][which] == rows[depth][which[0]]).all():
            depth += 1
        if depth == len(rows):
            return which
        v = rows[depth][which]
        if not ways[depth]:
            v = -np.unique(v, return_inverse=True)[1].reshape(-1) if v.dtype == object else (~v if v.dtype.kind == "i" else -v)
        which = which[np.argsort(v, kind="stable")]
        v = rows[depth][which]
        edge = np.flatnonzero(np.concatenate([[True], v[1:] != v[:-1], [True]]))
        if depth + 1 < len(rows):
            for k in np.flatnonzero(np.diff(edge) > 1):
                which[edge[k]:edge[k + 1]] = sort(which[edge[k]:edge[k + 1]], depth + 1)
        return which

    return sort(some, 0)


def natural_runs(rows: list[np.ndarray], ways: list[bool], src: np.ndarray) -> list[np.ndarray]:
    """Stretches of rows that are in order as they came and from one source."""
    if not len(src):
        return []
    cut = np.flatnonzero(~before_next(rows, ways) | (src[1:] != src[:-1])) + 1
    return np.split(np.arange(len(src)), cut)


def merge_partitions(df: DataFrame, key: KeySpec, fan_in: int = 64, scratch: bool = False) -> DataFrame:
    """Every partition as one sorted run with positions ``_ms_pos``, merged from the runs of its sources (``_ms_src``).

    Runs are taken as the exchange hands them over; where it breaks one up,
    its pieces count as runs. More than ``fan_in`` runs take several passes.
    With ``scratch`` runs are not made use of. A partition must fit a worker's
    memory (size p accordingly).
    """
    codes = Codes(df, key)
    columns = [c for c in df.columns if c != "_ms_src"]
    schema = T.StructType([*(df.schema[c] for c in columns), T.StructField("_ms_pos", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        whole = pa.Table.from_batches(held)
        first = len(columns) + 1
        rows, ways = codes.arrays(*codes.read([whole.column(i) for i in range(first, whole.num_columns)]))
        order = lex_order(rows, ways) if scratch else merged_order(rows, ways, natural_runs(rows, ways, whole.column("_ms_src").to_numpy()), fan_in)[0]
        out = whole.select(columns).take(pa.array(order)).append_column("_ms_pos", pa.array(np.arange(len(order))))
        yield from out.combine_chunks().to_batches(max_chunksize=10_000)

    return df.select(*columns, "_ms_src", *codes.named()).mapInArrow(run, schema)
