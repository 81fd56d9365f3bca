"""Sorts to compare with: single-level, central sampling, quicksort and two-way merging, and Spark's own."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tiersort.functions.keys import KeySpec
from tiersort.operators.layout import SortedLayout
from tiersort.operators.sort import Report, merge_sort, splitter_sort
from tiersort.plans.topology import factors


def single_sample_sort(df: DataFrame, key: KeySpec, p: int, oversample: float = 32, **options) -> SortedLayout:
    """One level, one bucket for each PE: p - 1 splitters and one exchange among all PEs."""
    return splitter_sort(df, key, p, 1, a=oversample, b=1, **options)


def single_merge_sort(df: DataFrame, key: KeySpec, p: int, merge: str = "arrow", **options) -> SortedLayout:
    """One level of exact splitting: p - 1 selections at once and one exchange; ``merge='resort'`` sorts what arrives from scratch."""
    return merge_sort(df, key, p, 1, merge=merge, **options)


def central_multilevel_sort(df: DataFrame, key: KeySpec, p: int, k: int = 2, a: float = 64, **options) -> SortedLayout:
    """Several levels with the sample sorted in one place, no overpartitioning and plain delivery."""
    return splitter_sort(df, key, p, k, a=a, b=1, sample_sort="central", delivery="prefix", **options)


def merge_every_level_sort(df: DataFrame, key: KeySpec, p: int, **options) -> SortedLayout:
    """A merging level for every factor of p: few messages, many moves."""
    return merge_sort(df, key, p, levels=factors(p), **options)


def parallel_quicksort(df: DataFrame, key: KeySpec, p: int, sample: float = 16, **options) -> SortedLayout:
    """One pivot for each group and level: log2 p moves."""
    return splitter_sort(df, key, p, levels=[2] * (p.bit_length() - 1), a=sample, b=1, **options)


def parallel_mergesort(df: DataFrame, key: KeySpec, p: int, **options) -> SortedLayout:
    """Exact halving on each level."""
    return merge_sort(df, key, p, levels=[2] * (p.bit_length() - 1), **options)


def spark_sort(df: DataFrame, key: KeySpec, p: int) -> SortedLayout:
    """Spark's range partitioning and local sort.

    Its splitters are sampled anew in every job and its partition numbers are
    no function of the rows, so the placed rows are cached: for comparisons,
    not for plans that must survive lost executors.
    """
    placed = df.repartitionByRange(p, *key.order()).withColumn("_ms_pe", F.spark_partition_id()).persist()
    return SortedLayout(placed.sortWithinPartitions(*key.order()), key, p, Report(kept=[placed]))
