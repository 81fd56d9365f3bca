"""Experiment workloads: metric rows for sorts, balance, delivery and scaling."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tiersort.functions.costmodel import fit, throughput
from tiersort.functions.keys import KeySpec, key
from tiersort.operators import delivery as d
from tiersort.operators.packing import pack
from tiersort.operators.sort import merge_sort, splitter_sort
from tiersort.operators.splitters import choose_splitters, classify, draw_sample, sort_sample
from tiersort.plans.topology import plan_levels
from tiersort.sources.sinks import discard, measure_only, staged
from tiersort.sources.tables import few_large, rand64, tiny_run


def ab_grid(df: DataFrame, by: KeySpec, unique: str, r: int, many_a: list[float], many_b: list[int], seeds: tuple[int, ...] = (0,)) -> DataFrame:
    """Rows (a, b, seed, sample, eps): imbalance after packing; nothing is shipped."""
    rows = df.withColumn("_ms_grp", F.lit(0)).persist()
    n, out = rows.count(), []
    for seed in seeds:
        for a in many_a:
            for b in many_b:
                m = int(a * b * r)
                splitters = choose_splitters(sort_sample(draw_sample(rows, m, unique, n, seed=seed), by, "_ms_grp"), by, "_ms_grp", b * r)
                counts = {x[0]: x[1] for x in classify(rows, splitters, by).groupBy("bucket").count().collect()}  # b*r numbers
                limit, _ = pack([counts.get(i, 0) for i in range(b * r)], r)
                out.append((float(a), b, seed, m, limit * r / n - 1))
    rows.unpersist()
    return df.sparkSession.createDataFrame(out, "a double, b int, seed int, sample int, eps double")


def delivery_worst(spark: SparkSession, case: str, p: int, r: int) -> DataFrame:
    """Rows (method, messages and words) of an adversarial piece table: ``tiny_run`` or ``few_large``."""
    pieces = staged(tiny_run(spark, p, r, 0, p - r) if case == "tiny_run" else few_large(spark, p, r), "pieces")
    out = None
    for method in ("prefix", "permuted", "chunked", "two_phase"):
        one = d.message_stats(d.deliver(pieces, method, pes=p)).withColumn("method", F.lit(method))
        out = one if out is None else out.unionByName(one)
    return out


def weak_scaling(spark: SparkSession, per_pe: list[int], ps: list[int], ks: list[int], repeat: int = 5, algorithms: tuple[str, ...] = ("splitter", "merge"), cores: int | None = None,
                 keys: DataFrame | None = None) -> DataFrame:
    """Rows (algorithm, per_pe, p, k, run, seconds, rate) of sorts of random 64-bit keys; ``rate`` in elements a second and core.

    ``keys``, rows (id, key), are sorted instead if given: those with the n * p
    smallest ids. Session, input and plans are made before the timer starts.
    """
    out, cores = [], cores or spark.sparkContext.defaultParallelism
    for n in per_pe:
        for p in ps:
            df = staged(rand64(spark, n * p) if keys is None else keys.orderBy("id").limit(n * p), "keys")
            rows = n * p if keys is None else df.count()
            for k in ks:
                levels = plan_levels(p, k)
                if k != "log" and len(levels) != k:
                    continue  # this plan is another k's
                for name in algorithms:
                    for run in range(repeat):
                        t = time.time()
                        sort = splitter_sort if name == "splitter" else merge_sort
                        layout = sort(df, key("key", ties=("id",)), p, levels=levels)
                        measure_only(layout.df)
                        s = time.time() - t
                        out.append((name, n, p, len(levels), run, s, throughput(rows, s, cores)))
                        layout.release()
            discard(df)
    return spark.createDataFrame(out, "algorithm string, per_pe int, p int, k int, run int, seconds double, rate double")


def phases(df: DataFrame, by: KeySpec, p: int, ks: tuple[int, ...] = (1, 2)) -> DataFrame:
    """Rows (algorithm, k, phase, seconds): time by phase, summed over the levels; every phase ends before the next begins."""
    out = []
    for k in ks:
        for name, sort in (("splitter", splitter_sort), ("merge", merge_sort)):
            report = sort(df, by, p, k, measure=True).report
            for phase in ("splitter selection", "bucket processing", "data delivery", "local sort"):
                out.append((name, k, phase, float(sum(r["seconds"] for r in report.rows if r["phase"] == phase))))
            report.release()
    return df.sparkSession.createDataFrame(out, "algorithm string, k int, phase string, seconds double")


def level_traffic(df: DataFrame, by: KeySpec, p: int, ks: tuple[int, ...] = (1, 2, 3), **options) -> DataFrame:
    """Rows (k, level, groups, max_sent, max_recv, bottleneck, words, eps) of splitter sorts by level."""
    out = []
    for k in ks:
        report = splitter_sort(df, by, p, k, **options).report
        out += [(k, r["level"], r["groups"], r["max_sent"], r["max_recv"], r["bottleneck"], r["words"], r["eps"]) for r in report.rows if r["phase"] == "data delivery"]
        report.release()
    return df.sparkSession.createDataFrame(out, "k int, level int, groups int, max_sent double, max_recv double, bottleneck double, words double, eps double")


def tie_modes(df: DataFrame, columns: list[str], p: int, modes: tuple[str, ...] = ("none", "level", "origin")) -> DataFrame:
    """Rows (key, mode, eps): imbalance of one level of splitting by keys that repeat."""
    out = []
    for c in columns:
        for mode in modes:
            layout = splitter_sort(df.select(c), key(c), p, 1, ties=mode)
            out.append((c, mode, float(max(layout.loads) * p / max(1, sum(layout.loads)) - 1)))
            layout.release()
    return df.sparkSession.createDataFrame(out, "key string, mode string, eps double")


def best_k(metrics: DataFrame) -> DataFrame:
    """Median by level count, and of these the best, for each algorithm and size."""
    med = metrics.groupBy("algorithm", "per_pe", "p", "k").agg(F.median("seconds").alias("median"))
    return med.groupBy("algorithm", "per_pe", "p").agg(F.min_by("k", "median").alias("k"), F.min("median").alias("median"))


def slowdown(metrics: DataFrame) -> DataFrame:
    """Ratio of the merging to the splitting sort, each at its best."""
    best = best_k(metrics)
    a, b = best.where("algorithm = 'merge'"), best.where("algorithm = 'splitter'").select("per_pe", "p", F.col("median").alias("other"))
    return a.join(b, ["per_pe", "p"]).select("per_pe", "p", (F.col("median") / F.col("other")).alias("ratio"))


def fluctuation(metrics: DataFrame) -> DataFrame:
    return metrics.groupBy("algorithm", "per_pe", "p", "k").agg(*[F.percentile("seconds", q).alias(f"q{int(q * 100)}") for q in (0.0, 0.25, 0.5, 0.75, 1.0)], F.stddev("seconds").alias("sd"))


def efficiencies(metrics: DataFrame) -> DataFrame:
    """Weak-scaling efficiency of the best level counts, against the fewest PEs of the same load."""
    best = best_k(metrics)
    first = Window.partitionBy("algorithm", "per_pe").orderBy("p")
    return best.withColumn("efficiency", F.first("median").over(first) / F.col("median"))


def cost_fit(reports: list[list[dict]]) -> tuple[float, float]:
    """Start-up and time for each word from the deliveries of several sorts."""
    return fit([(r["max_sent"], r["bottleneck"], r["seconds"]) for rows in reports for r in rows if r.get("phase") == "data delivery"])
