"""User-defined functions for SQL: curve keys, level plans, schedules."""

from __future__ import annotations

import sys

import numpy as np
import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from tiersort.plans import topology

cloudpickle.register_pickle_by_value(sys.modules[__name__])  # executors need not have the package
cloudpickle.register_pickle_by_value(topology)


def hilbert(x: np.ndarray, y: np.ndarray, bits: int) -> np.ndarray:
    """Places of cells (x, y) on the plane-filling curve of ``bits`` levels."""
    x, y, out = x.astype(np.int64).copy(), y.astype(np.int64).copy(), np.zeros(len(x), np.int64)
    for b in range(bits - 1, -1, -1):
        rx, ry = (x >> b) & 1, (y >> b) & 1
        out += ((3 * rx) ^ ry) << (2 * b)
        low = (1 << b) - 1
        x, y = x & low, y & low
        flip = (ry == 0) & (rx == 1)
        x, y = np.where(flip, low - x, x), np.where(flip, low - y, y)
        swap = ry == 0
        x, y = np.where(swap, y, x), np.where(swap, x, y)
    return out


def hilbert_key(bits: int):
    @F.pandas_udf("long")
    def key(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series(hilbert(x.to_numpy(), y.to_numpy(), bits))

    return key


def median_of(column: str):
    """Median of a group, as an aggregate over Arrow batches."""
    @F.pandas_udf("double")
    def median(x: pd.Series) -> float:
        return float(x.median())

    return median(F.col(column))


class LevelPlan:
    def eval(self, p: int, k: int, how: str):
        yield from enumerate(topology.plan_levels(p, k, how))


class OneFactor:
    def eval(self, p: int):
        for t in range(p):
            for i in range(p):
                if (t - i) % p != i:
                    yield t, i, (t - i) % p


def register(spark: SparkSession, bits: int = 16) -> None:
    """Makes ``level_plan(p, k, how)``, ``one_factor(p)`` and ``hilbert_key(x, y)`` known to SQL."""
    spark.udtf.register("level_plan", F.udtf(LevelPlan, returnType="level int, r int"))
    spark.udtf.register("one_factor", F.udtf(OneFactor, returnType="round int, src int, dst int"))
    spark.udf.register("hilbert_key", hilbert_key(bits))
