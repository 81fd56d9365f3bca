"""Packing consecutive buckets into at most r groups with the least largest load."""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Sequence
from itertools import accumulate

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def scan_pack(sizes: Sequence[int], limit: int, weights: Sequence[float] | None = None) -> list[int] | None:
    """Group of each bucket if every group takes buckets until the next would pass ``limit``; None if one bucket is over it.

    ``weights`` scale the limit of each group (unequal numbers of PEs).
    """
    out, group, load = [], 0, 0
    for s in sizes:
        while load and load + s > limit * (weights[min(group, len(weights) - 1)] if weights else 1):
            group, load = group + 1, 0
        if s > limit * (weights[min(group, len(weights) - 1)] if weights else 1):
            return None
        load += s
        out.append(group)
    return out


def _groups(sizes: Sequence[int], limit: int, weights: Sequence[float] | None = None) -> int:
    got = scan_pack(sizes, limit, weights)
    return len(sizes) + 1 if got is None else got[-1] + 1 if got else 0


def _bounds(sizes: Sequence[int], r: int) -> tuple[int, int]:
    top = max(sizes, default=0)
    mean = -(-sum(sizes) // r)
    return max(top, mean), mean + top


def pack(sizes: Sequence[int], r: int, search: str = "jump", weights: Sequence[float] | None = None) -> tuple[int, list[int]]:
    """The least limit for which a scan needs at most r groups, and its groups.

    ``bisect`` halves the range of limits; ``jump`` only visits limits that
    are loads of some scan, finding each group's end in the prefix sums.
    """
    if not sizes:
        return 0, []
    if weights and len(set(weights)) > 1:
        low, high = 0, sum(sizes) + 1
        scale = min(w for w in weights if w > 0)
        high = int(high / scale) + 1
        while low < high:
            mid = (low + high) // 2
            if _groups(sizes, mid, weights) <= r:
                high = mid
            else:
                low = mid + 1
        return low, scan_pack(sizes, low, weights)
    low, high = _bounds(sizes, r)
    if search == "bisect":
        while low < high:
            mid = (low + high) // 2
            if _groups(sizes, mid) <= r:
                high = mid
            else:
                low = mid + 1
        return high, scan_pack(sizes, high)
    ahead = [0, *accumulate(sizes)]
    while low < high:
        mid = (low + high) // 2
        at, groups, largest, next_limit = 0, 0, 0, None
        while at < len(sizes) and groups <= r:
            end = bisect_right(ahead, ahead[at] + mid) - 1
            largest = max(largest, ahead[end] - ahead[at])
            if end < len(sizes):
                more = ahead[end + 1] - ahead[at]
                next_limit = more if next_limit is None else min(next_limit, more)
            at, groups = end, groups + 1
        if at == len(sizes) and groups <= r:
            high = largest
        else:
            low = max(next_limit, mid + 1)
    return high, scan_pack(sizes, high)


def pack_wide(spark: SparkSession, sizes: Sequence[int], r: int, fanout: int = 16) -> tuple[int, list[int]]:
    """As ``pack``: each round tests ``fanout`` limits at once, as rows of a DataFrame."""
    low, high = _bounds(sizes, r)
    given = F.array(*[F.lit(int(s)) for s in sizes])
    while low < high:
        tried = sorted({low + (high - low) * i // fanout for i in range(fanout)})
        rows = spark.createDataFrame([(x,) for x in tried], "l long")
        step = F.aggregate(given, F.struct(F.lit(1).alias("g"), F.lit(0).cast("long").alias("load")),
                           lambda acc, s: F.when(acc["load"] + s > F.col("l"), F.struct((acc["g"] + 1).alias("g"), s.cast("long").alias("load")))
                           .otherwise(F.struct(acc["g"].alias("g"), (acc["load"] + s).alias("load"))))
        fits = [x.l for x in rows.withColumn("g", step["g"]).where(F.col("g") <= r).select("l").collect()]
        best = min(fits, default=high)
        low = max([x + 1 for x in tried if x < best], default=low)
        high = best
    return high, scan_pack(sizes, high)


def packing_table(sizes: DataFrame, r: int) -> DataFrame:
    """Rows (grp, bucket, part, load_limit) for rows (grp, bucket, size); a group's buckets number b*r, independent of the data."""
    spark = sizes.sparkSession
    by: dict[int, list[tuple[int, int]]] = {}
    for row in sizes.select("grp", "bucket", "size").collect():
        by.setdefault(row.grp, []).append((row.bucket, row.size))
    out = []
    for g, rows in by.items():
        rows.sort()
        limit, parts = pack([s for _, s in rows], r)
        out += [(g, b, part, limit) for (b, _), part in zip(rows, parts)]
    return spark.createDataFrame(out, "grp int, bucket int, part int, load_limit long")
