"""Samples, small sorts, splitters and classification into buckets."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tiersort.functions.keys import KeySpec
from tiersort.functions.mixing import PRIME, h

#: Splitters that may be sent to every task; beyond it the classifying join is a shuffled one.
MOST_BROADCAST = 2_000_000
#: Rows of which every pair is compared in one broadcast join, and rows of a list in the blocks of a larger matrix.
MOST_MATRIX, MATRIX_BLOCK = 20_000, 500_000


def draw_sample(df: DataFrame, size: int, by: str, rows: int, grp: str | None = None, how: str = "hash", seed: int = 0) -> DataFrame:
    """About or exactly ``size`` rows of each group.

    ``hash`` takes the rows with the smallest mixed value of the integer column
    ``by``: SQL can repeat it, and tasks that run again draw the same. Rows far
    above the expected bound are dropped where they are read. ``bernoulli``
    takes each row with one probability.
    """
    if how == "bernoulli":
        return df.sample(False, min(1.0, size / max(1, rows)), seed)
    place = h(F.pmod(F.coalesce(F.col(by).cast("long"), F.lit(0).cast("long")) + seed, F.lit(PRIME).cast("long")))
    bound = min(PRIME, int(PRIME * min(1.0, (2 * size + 100) / max(1, rows))) + 1)
    order = Window.partitionBy(*([grp] if grp else [F.lit(0)])).orderBy("_ms_h", by)
    return (df.withColumn("_ms_h", place).where(F.col("_ms_h") < bound).withColumn("_ms_n", F.row_number().over(order))
            .where(F.col("_ms_n") <= size).drop("_ms_h", "_ms_n"))


def grid_shape(p: int, shape: str = "auto") -> tuple[int, int]:
    """Rows and columns of the PE grid: square, or the two nearest powers of two."""
    if shape == "square":
        a = max(1, math.isqrt(p))
        return a, a
    bits = max(0, p.bit_length() - 1)
    return 1 << -(-bits // 2), 1 << bits // 2


def grid_rank(df: DataFrame, key: KeySpec, p: int = 16, shape: str = "auto", pe: str | None = None, wanted: list[int] | None = None) -> DataFrame:
    """``df`` with ``rank`` (from 0) by comparing all pairs on a grid of PEs.

    Elements are dealt to a grid's PEs; each is copied along its row and along
    its column. In every cell both lists are sorted together, so a column's
    elements are ranked among a row's by a running count, and an element's rank
    is the sum over its column's cells. ``wanted`` keeps some ranks only. Keys
    must be unique. For small inputs (samples): an element is copied a + b
    times.
    """
    a, b = grid_shape(p, shape)
    names = key.names
    base = df.withColumn("_ms_pe", F.col(pe) % (a * b) if pe else F.pmod(F.xxhash64(*names), F.lit(a * b)).cast("int"))
    own = base.select(*names, (F.col("_ms_pe") % b).alias("col"), F.explode(F.sequence(F.lit(0), F.lit(a - 1))).alias("row"), F.lit(0).alias("_ms_s"))
    row = base.select(*names, F.explode(F.sequence(F.lit(0), F.lit(b - 1))).alias("col"), F.expr(f"_ms_pe div {b}").cast("int").alias("row"), F.lit(1).alias("_ms_s"))
    cell = Window.partitionBy("row", "col").orderBy(*key.order(), "_ms_s").rowsBetween(Window.unboundedPreceding, 0)
    counted = own.unionByName(row).withColumn("_ms_c", F.sum("_ms_s").over(cell)).where("_ms_s = 0")
    ranks = counted.groupBy(F.struct(*names).alias("_ms_r")).agg(F.sum("_ms_c").cast("long").alias("rank"))
    out = base.drop("_ms_pe").withColumn("_ms_id_", F.struct(*names)).join(ranks, F.col("_ms_id_").eqNullSafe(F.col("_ms_r"))).drop("_ms_id_", "_ms_r")
    return out.where(F.col("rank").isin(wanted)) if wanted is not None else out


def grid_sort(df: DataFrame, key: KeySpec, p: int = 16, shape: str = "auto"):
    """Layout of a small table: ranked on the grid, each element routed to PE rank * p div n."""
    from tiersort.operators.layout import SortedLayout

    n = df.count()
    pe = F.expr(f"cast(((rank + 1) * {p} - 1) div {max(1, n)} as int)")
    moved = grid_rank(df, key, p, shape).withColumn("_ms_pe", pe).drop("rank").repartitionById(p, F.col("_ms_pe"))
    return SortedLayout(moved.sortWithinPartitions("_ms_pe", *key.order()), key, p, loads=[n * (x + 1) // p - n * x // p for x in range(p)])


def grid_rank_matrix(df: DataFrame, key: KeySpec) -> DataFrame:
    """``df`` with ``rank`` by one comparison of each pair (the n x n case; for small inputs).

    Over MOST_MATRIX rows the matrix is cut into square blocks: every row's list
    meets every column's in one block, where both are sorted together.
    """
    n = df.count()
    if n > MOST_MATRIX:
        side = max(4, -(-n // MATRIX_BLOCK))
        return grid_rank(df, key, side * side, "square")
    side = df.select(key.struct().alias("_ms_o"))
    own = df.withColumn("_ms_id", F.struct(*key.names))
    ranks = own.join(F.broadcast(side), key.above(F.col("_ms_o")), "left").groupBy("_ms_id").agg(F.count("_ms_o").alias("rank"))
    return df.withColumn("_ms_k", F.struct(*key.names)).join(ranks, F.col("_ms_k").eqNullSafe(F.col("_ms_id"))).drop("_ms_k", "_ms_id")


def sort_sample(sample: DataFrame, key: KeySpec, grp: str, how: str = "central", p: int = 16) -> DataFrame:
    """Sample rows with ``rank`` (from 1) in their group: by one window for each group, or on the grid."""
    if how == "grid":
        ranked = grid_rank(sample, KeySpec((grp, *key.cols), (True, *key.asc) if key.asc else (), (True, *(key.nulls_first or key.asc or (True,) * len(key.cols))), key.ties), p)
        first = ranked.groupBy(F.col(grp).alias("_ms_g")).agg(F.min("rank").alias("_ms_f"))
        return ranked.join(F.broadcast(first), F.col(grp) == F.col("_ms_g")).withColumn("rank", F.col("rank") - F.col("_ms_f") + 1).drop("_ms_g", "_ms_f")  # a row for each group
    return sample.withColumn("rank", F.row_number().over(Window.partitionBy(grp).orderBy(*key.order())).cast("long"))


def choose_splitters(ranked: DataFrame, key: KeySpec, grp: str, buckets: Column | int) -> DataFrame:
    """Rows (grp, splitters): the sample keys of ranks ceil(i*m/buckets), i = 1 .. buckets-1, in order."""
    br = buckets if isinstance(buckets, Column) else F.lit(buckets)
    rows = ranked.withColumn("_ms_m", F.count("*").over(Window.partitionBy(grp))).withColumn("_ms_b", br)
    # rank x is taken for every i with ceil(i*m/b) = x: i in (  (x-1)*b/m , x*b/m ]
    low, high = F.expr("(rank - 1) * _ms_b div _ms_m + 1"), F.expr("least(rank * _ms_b div _ms_m, _ms_b - 1)")
    rows = rows.withColumn("_ms_lo", low).withColumn("_ms_hi", high).where("_ms_hi >= _ms_lo")
    picked = rows.select(F.col(grp).alias("grp"), F.explode(F.sequence("_ms_lo", "_ms_hi")).alias("i"), key.struct().alias("s"))
    return picked.groupBy("grp").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "s")), lambda x, y: (x["i"] - y["i"]).cast("int")), lambda x: x["s"]).alias("splitters"))


def _two_to(bits: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1), bits)


def tree_of(splitters: Column) -> tuple[Column, Column]:
    """Splitters as an implicit search tree (root first) and its depth; short levels are padded by the last splitter."""
    n = F.size(splitters)
    depth = F.ceil(F.log2(n + F.lit(1.0))).cast("int")
    node = F.sequence(F.lit(1), _two_to(depth) - 1)

    def at(i: Column) -> Column:
        level = F.floor(F.log2(i.cast("double")) + 1e-9).cast("int")  # levels above this node
        span = _two_to(depth - level)
        place = (i - _two_to(level)) * span + F.shiftright(span, 1)  # in-order place, from 1
        return F.element_at(splitters, F.least(n, place))
    return F.transform(node, at), depth


def classify(df: DataFrame, splitters: DataFrame, key: KeySpec, grp: str = "_ms_grp", how: str = "tree", out: str = "bucket", broadcast: bool = True) -> DataFrame:
    """``df`` with its bucket: the number of its group's splitters that are strictly before its key.

    ``tree`` walks the implicit search tree in one expression, ``scan`` counts
    over the splitters. ``splitters`` has a row (grp, splitters) for each group
    that is split; rows of other groups get bucket 0.
    """
    if how == "tree":
        tree, depth = tree_of(F.col("splitters"))
        table = splitters.where(F.size("splitters") > 0).select(F.col("grp").alias("_ms_sg"), tree.alias("_ms_tree"), depth.alias("_ms_depth"), F.size("splitters").alias("_ms_n"))
    else:
        table = splitters.select(F.col("grp").alias("_ms_sg"), F.col("splitters").alias("_ms_tree"))
    joined = df.join(F.broadcast(table) if broadcast else table, F.col(grp) == F.col("_ms_sg"), "left")
    if how == "tree":
        walk = F.aggregate(F.sequence(F.lit(1), F.col("_ms_depth")), F.lit(1), lambda i, _: i * 2 + key.above(F.element_at("_ms_tree", i)).cast("int"))
        bucket = F.least(F.col("_ms_n"), walk - _two_to(F.col("_ms_depth")))
    else:
        bucket = F.aggregate("_ms_tree", F.lit(0), lambda c, s: c + key.above(s).cast("int"))
    return joined.withColumn(out, F.coalesce(bucket, F.lit(0)).cast("int")).drop("_ms_sg", "_ms_tree", "_ms_depth", "_ms_n")


def classify_arrow(df: DataFrame, splitters: DataFrame, key: KeySpec, grp: str = "_ms_grp", out: str = "bucket") -> DataFrame:
    """As ``classify``, by binary search over Arrow batches; for ascending numeric keys without nulls.

    Rows equal to splitters in one column go on with the next column, all
    rows of such a run at once. The splitters (b*r for each group) are on the
    driver; a scalar function keeps the rows' partitioning.
    """
    names = key.names
    held = {r.grp: np.array([tuple(s) for s in r.splitters]).reshape(len(r.splitters), len(names)).T for r in
            splitters.select("grp", "splitters").collect()} if _exact(df, names) else None
    if held is None or not all(asc for _, asc, _ in key._all):
        return classify(df, splitters, key, grp, out=out)
    sent = df.sparkSession.sparkContext.broadcast(held)

    def search(cols: list, rows, table, low: int, high: int, depth: int, result) -> None:
        part = table[depth][low:high]
        v = cols[depth][rows]
        a, b = np.searchsorted(part, v, "left"), np.searchsorted(part, v, "right")
        result[rows] = low + a
        if depth + 1 < len(cols):
            tied = np.flatnonzero(b > a)
            for x in np.unique(a[tied]):
                mine = tied[a[tied] == x]
                search(cols, rows[mine], table, low + int(x), low + int(b[mine[0]]), depth + 1, result)

    def run(group: pd.Series, *columns: pd.Series) -> pd.Series:
        cols, g = [c.to_numpy() for c in columns], group.to_numpy()
        result = np.zeros(len(g), np.int64)
        for x in np.unique(g):
            if x in sent.value:
                search(cols, np.flatnonzero(g == x), sent.value[x], 0, sent.value[x].shape[1], 0, result)
        return pd.Series(result)

    return df.withColumn(out, F.pandas_udf(run, "int")(F.col(grp), *names))


def _exact(df: DataFrame, names: list[str]) -> bool:
    """Whether all columns fit doubles or are integers, so that one array holds a splitter's columns without loss."""
    kinds = {df.schema[c].dataType.simpleString() for c in names}
    return kinds <= {"int", "bigint", "smallint", "tinyint"} or kinds <= {"double", "float", "int", "smallint", "tinyint"}


def bucket_sizes(df: DataFrame, grp: str = "_ms_grp", bucket: str = "bucket") -> DataFrame:
    return df.groupBy(F.col(grp).alias("grp"), F.col(bucket).alias("bucket")).agg(F.count("*").alias("size"))
