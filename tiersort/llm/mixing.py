"""Mixing sources to target weights by entropy balancing.

Rates as near as possible (in relative entropy) to one for each document, such
that the words of every constraint group meet a target, are exponentials of a
sum of one multiplier for each group. The multipliers minimise a convex dual;
Newton steps find them. Documents of equal groups have equal rates, so they
are first aggregated into cells; each step then aggregates the gradient and
the Hessian over the cells. With one column of groups the Hessian is diagonal
and the multipliers stay in a table, whatever their number (``balance_each``,
which the mix uses); several columns share one bounded system (``balance``).

Rates become copies: each document of a cell gets the whole part, and in a
fixed pseudo-random order the first documents get one more until the words of
the cell are used up, the last of them in part. Prefix sums run over 1024
ranges of that order for each group, so a source with a third of all
documents is not sorted in one task.

Null text has no words, null sources form one group (last in order). Sources
without words get target 0. Repeated rows share a place in the order and are
interchangeable. An empty table gives no row; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tiersort.llm.common import discard, staged, word_count

MOST_TIMES = 3
RANGES = 21  # bits of the order below a range: 2^31 places in 1024 ranges


def place(doc_id: Column) -> Column:
    """Position in a fixed pseudo-random order; SQL can repeat it."""
    low = F.pmod(F.coalesce(doc_id.cast("long"), F.lit(0).cast("long")), F.lit(2147483647).cast("long"))
    return F.pmod((low + 1) * 1103515245, F.lit(2147483647).cast("long"))


def targets(sources: DataFrame, weights: tuple[int, ...] = (5, 2, 1), most: int = MOST_TIMES) -> DataFrame:
    """Rows (source, source_size, target) for rows (source, source_size).

    Weights repeat over the sources in code point order. The total is shared
    by weight; what a source's bound leaves over is shared again. That ends at
    one level of words for each unit of weight, found by prefix sums in the
    order of bound per weight. Runs over one row for each source.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    w = F.element_at(F.array(*[F.lit(x) for x in weights]), ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int"))
    s = sources.withColumn("w", w).withColumn("bound", F.col("source_size") * most)
    fill = Window.orderBy(F.col("bound") / F.col("w"), F.col("source").asc_nulls_last())
    before = fill.rowsBetween(Window.unboundedPreceding, -1)
    every = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    s = s.select("*", F.sum("source_size").over(every).alias("total"), F.coalesce(F.sum("bound").over(before), F.lit(0)).alias("used"),
                 (F.sum("w").over(every) - F.coalesce(F.sum("w").over(before), F.lit(0))).alias("open"))
    s = s.withColumn("level", (F.col("total") - F.col("used")).cast("double") / F.col("open"))
    # holding further sources at their bound than need be only lowers the level
    level = F.max(F.when(F.col("level") * F.col("w") <= F.col("bound"), F.col("level"))).over(every)
    return s.withColumn("lev", level).select("source", "source_size", F.least(F.col("bound").cast("double"), F.col("lev") * F.col("w")).alias("target"))


def balance_each(cells: DataFrame, targets: DataFrame, group: str, size: str = "size", close: float = 1e-13, most_steps: int = 2_000) -> DataFrame:
    """Rows (group, target, rate): the words of ``cells`` (group, size) times the rate meet ``targets`` (group, target).

    One Newton iteration over all groups: each step aggregates every group's
    tilted words (its gradient is these less the target, its Hessian entry
    these) and moves its multiplier, by 2 at most. A target of 0 or a group
    without words has rate 0. From 0 a multiplier falls by about 1 a step
    towards the logarithm of a small rate, so the steps needed are few.
    """
    words = cells.groupBy(F.col(group).alias("_g")).agg(F.sum(size).cast("double").alias("_words"))
    joined = targets.join(words, F.col(group).eqNullSafe(F.col("_g")), "left").drop("_g")
    start = F.when((F.col("target") > 0) & (F.col("_words") > 0), F.lit(0.0))
    now = staged(joined.select(group, "target", "_words", start.alias("_x")), "newton0")
    for step in range(1, most_steps + 1):
        tilted = F.col("_words") * F.exp("_x")
        gap = F.abs(tilted - F.col("target")) / F.col("target")
        if (now.agg(F.max(gap)).first()[0] or 0.0) <= close:
            break
        move = (F.col("target") - tilted) / tilted
        after = staged(now.withColumn("_x", F.col("_x") + F.greatest(F.lit(-2.0), F.least(F.lit(2.0), move))), f"newton{step}")
        discard(now)
        now = after
    return now.select(group, "target", F.coalesce(F.exp("_x"), F.lit(0.0)).alias("rate"))


def balance(cells: DataFrame, margins: dict[str, dict], size: str = "size", most_steps: int = 200, close: float = 1e-9,
            most_groups: int = 4000) -> DataFrame:
    """``cells`` with a ``rate``: words of every group of every margin column meet its target.

    ``margins`` maps a column to {group: target words}; their number is
    bounded by ``most_groups``. Each Newton step is one aggregation over the
    cells, whose result has one row for each pair of groups that meet.
    """
    keys = [(c, g) for c, t in margins.items() for g in t]
    if len(keys) > most_groups:
        raise ValueError(f"{len(keys)} constraint groups; at most {most_groups}")
    number, want = {k: i for i, k in enumerate(keys)}, np.array([float(margins[c][g]) for c, g in keys])
    x = np.zeros(len(keys))

    def rated(x: np.ndarray) -> DataFrame:
        total = F.lit(0.0)
        for c, t in margins.items():
            table = F.create_map(*[F.lit(v) for g in t for v in (g, float(x[number[c, g]]))])
            total = total + table[F.col(c)]
        return cells.withColumn("rate", F.exp(total))

    def sums(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        got = np.zeros((len(keys), len(keys)))
        names = list(margins)
        for row in rated(x).groupBy(*names).agg(F.sum(F.col("rate") * F.col(size)).alias("m")).collect():
            at = [number[c, row[c]] for c in names]
            got[np.ix_(at, at)] += row.m
        return got, got.diagonal() - want

    for _ in range(most_steps):
        hessian, gradient = sums(x)
        if np.abs(gradient).max() <= close * max(1.0, want.max()):
            break
        step = np.linalg.lstsq(hessian, -gradient, rcond=1e-12)[0]
        x = x + step * min(1.0, 2.0 / max(1e-12, np.abs(step).max()))
    return rated(x)


def rounded(docs: DataFrame, group: str, size: str = "size", rate: str = "rate", doc_id: str = "doc_id") -> DataFrame:
    """``docs`` with ``taken``: words taken of each document, repeats counted.

    ``rate`` is the same within a group; the taken words of a group are its
    size times the rate, to the nearest word.
    """
    at = place(F.col(doc_id))
    rows = docs.withColumn("_at", at).withColumn("_range", F.shiftright("_at", RANGES))
    parts = rows.groupBy(group, "_range").agg(F.sum(size).alias("_part"))
    ahead = Window.partitionBy(group).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    parts = parts.select(F.col(group).alias("_g"), F.col("_range").alias("_r"), F.coalesce(F.sum("_part").over(ahead), F.lit(0)).alias("_ahead"),
                         F.sum("_part").over(Window.partitionBy(group)).alias("_all"))
    inside = Window.partitionBy(group, "_range").orderBy("_at", doc_id, size).rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("_in", F.coalesce(F.sum(size).over(inside), F.lit(0)))
    rows = rows.join(parts, F.col(group).eqNullSafe(F.col("_g")) & (F.col("_range") == F.col("_r")))
    whole = F.floor(F.col(rate) + 1e-9)
    more = F.round(F.col(rate) * F.col("_all")).cast("long") - whole * F.col("_all")
    part = F.least(F.col(size), F.greatest(F.lit(0), more - F.col("_ahead") - F.col("_in")))
    return rows.withColumn("taken", (whole * F.col(size) + part).cast("long")).drop("_at", "_range", "_in", "_g", "_r", "_ahead", "_all")


def mix(docs: DataFrame, doc_id: str = "doc_id", text_col: str = "text", source_col: str = "source",
        weights: tuple[int, ...] = (5, 2, 1), most: int = MOST_TIMES, carry: tuple[str, ...] = ()) -> DataFrame:
    """Rows (doc_id, source, size, source_size, target, taken) and the columns of ``carry``; a row for each input row."""
    sized = staged(docs.select(*carry, F.col(doc_id).alias("doc_id"), F.col(source_col).alias("source"), word_count(F.col(text_col)).alias("size")), "sizes")
    cells = staged(sized.groupBy("source").agg(F.sum("size").alias("source_size")), "cells")
    wanted = staged(targets(cells, weights, most), "targets")
    rates = balance_each(cells, wanted.select("source", "target"), "source", "source_size").select(F.col("source").alias("_s"), "target", "rate")
    rates = rates.join(wanted.select(F.col("source").alias("_t"), "source_size"), F.col("_s").eqNullSafe(F.col("_t"))).drop("_t")
    rated = sized.join(rates, F.col("source").eqNullSafe(F.col("_s"))).drop("_s")
    return rounded(rated, "source").select(*carry, "doc_id", "source", "size", "source_size", "target", "taken")


ORACLE = r"""
with d as (select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size,
                  ((doc_id % 2147483647 + 1) * 1103515245) % 2147483647 as place from documents),
s as (select source, sum(size)::bigint as source_size from d group by source),
w as (select *, [5, 2, 1][((row_number() over (order by source asc nulls last) - 1) % 3 + 1)::int] as w, 3 * source_size as bound from s),
f as (select *, sum(source_size) over () as total,
             coalesce(sum(bound) over (order by bound / w, source asc nulls last rows between unbounded preceding and 1 preceding), 0) as used,
             sum(w) over () - coalesce(sum(w) over (order by bound / w, source asc nulls last rows between unbounded preceding and 1 preceding), 0) as free
      from w),
l as (select *, (total - used)::double / free::double as level from f),
v as (select max(level) as lev from l where level * w <= bound),
t as (select source, source_size, least(bound::double, lev * w) as target from l, v),
c as (select d.*, source_size, target, case when source_size > 0 then floor(target / source_size + 1e-9)::bigint else 0 end as whole,
             coalesce(sum(size) over (partition by d.source order by place, doc_id, size rows between unbounded preceding and 1 preceding), 0)::bigint as ahead
      from d join t on d.source is not distinct from t.source)
select doc_id, size, source_size, target,
       (whole * size + least(size, greatest(0, round(target)::bigint - whole * source_size - ahead)))::bigint as taken
from c"""
