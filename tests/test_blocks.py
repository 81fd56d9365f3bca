"""Hand examples and invariants of the building blocks."""

import random
import signal

import pytest
from pyspark.sql import functions as F

from tiersort.functions import costmodel
from tiersort.functions.keys import key
from tiersort.operators import delivery as d
from tiersort.operators.packing import pack, pack_wide, scan_pack
from tiersort.operators.selection import select_splits
from tiersort.operators.sort import merge_sort
from tiersort.operators.splitters import classify, grid_rank, grid_rank_matrix
from tiersort.plans.topology import group_range, per_level_eps, plan_levels, suggest_ab
from tiersort.sources.tables import few_large, tiny_run
from tiersort.streaming.runs import merge_runs


def test_packing_by_hand(spark):
    sizes = [5, 3, 4, 2, 6, 1]
    assert pack(sizes, 3) == pack(sizes, 3, "bisect") == pack_wide(spark, sizes, 3) == (8, [0, 0, 1, 1, 2, 2])
    assert scan_pack(sizes, 7)[-1] + 1 == 4 and scan_pack(sizes, 12)[-1] + 1 == 2


def test_packing_is_least():
    rng = random.Random(1)
    for _ in range(300):
        sizes = [rng.randrange(20) for _ in range(rng.randrange(1, 12))]
        r = rng.randrange(1, 6)
        least = next(x for x in range(sum(sizes) + 1) if (g := scan_pack(sizes, x)) is not None and g[-1] < r)
        assert pack(sizes, r)[0] == pack(sizes, r, "bisect")[0] == least


def test_level_plans():
    table = {512: [8, 4, 16], 2048: [16, 8, 16], 8192: [32, 16, 16], 32768: [64, 32, 16]}
    for p, plan in table.items():
        assert plan_levels(p, 3, "node") == plan and plan_levels(p, 2, "node") == [p // 16, 16] and plan_levels(p, 1) == [p]
    for p in (1, 6, 7, 12, 16, 30):
        for k in (1, 2, 3, "log", "auto"):
            plan = plan_levels(p, k)
            product = 1
            for r in plan:
                product *= r
            assert product == p
    assert [group_range(0, 10, 3, j) for j in range(3)] == [(0, 3), (3, 3), (6, 4)]
    assert suggest_ab(0.1, 16)[1] == 20 and abs((1 + per_level_eps(0.2, 2)) ** 2 - 1.2) < 1e-12


def test_classify_by_hand(spark):
    rows = spark.createDataFrame([(x,) for x in (1, 15, 20, 25, 70, 75, 99)], "x int").withColumn("_ms_grp", F.lit(0))
    table = spark.createDataFrame([(0, [(x,) for x in range(10, 80, 10)])], "grp int, splitters array<struct<k0:int>>")
    for how in ("tree", "scan"):
        assert [r.bucket for r in classify(rows, table, key("x"), how=how).orderBy("x").collect()] == [0, 1, 1, 2, 6, 7, 7]
    for n in range(1, 12):
        table = spark.createDataFrame([(0, [(3 * i,) for i in range(n)])], "grp int, splitters array<struct<k0:int>>")
        got = {r.x: r.bucket for r in classify(rows, table, key("x")).collect()}
        assert got == {x: sum(3 * i < x for i in range(n)) for x in got}


@pytest.mark.parametrize("p", [1, 4, 6, 8])
def test_grid_rank(spark, p):
    rows = spark.createDataFrame([(i, (i * 37) % 50) for i in range(40)], "id int, x int")
    by = key("x", ties=("id",))
    want = {i: k for k, (_, i) in enumerate(sorted(((i * 37) % 50, i) for i in range(40)))}
    for out in (grid_rank(rows, by, p), grid_rank_matrix(rows, by)):
        assert {r.id: r["rank"] for r in out.collect()} == want
    assert grid_rank(rows.limit(0), by, p).count() == 0


def test_selection_by_hand(spark):
    rows = [(e, i, x) for e, xs in enumerate(([1, 4, 7], [2, 3, 9], [5, 6, 8])) for i, x in enumerate(xs)]
    runs = spark.createDataFrame(rows, "_ms_pe int, _ms_pos long, x int").withColumn("_ms_grp", F.lit(0))
    for m in (1, 4):
        for k, want in {5: (2, 2, 1), 0: (0, 0, 0), 9: (3, 3, 3), 1: (1, 0, 0)}.items():
            assert tuple(select_splits(runs, key("x"), {0: [k]}, pivots_per_round=m)[0, k].values()) == want


PIECES = [(e, g, s) for e, (a, b) in enumerate(((3, 1), (2, 2), (1, 3), (2, 2))) for g, s in ((0, a), (2, b))]


def rows_of(df):
    return sorted((r.grp, r.pe, r.from_pos, r.to_pos, r.target) for r in df.collect())


def test_delivery_by_hand(spark):
    pieces = spark.createDataFrame([(e, g, s, g, 2) for e, g, s in PIECES], "pe int, grp int, size long, base int, q int")
    assert [(g, e, b - a, t) for g, e, a, b, t in rows_of(d.deliver(pieces, "prefix"))] == [
        (0, 0, 3, 0), (0, 1, 1, 0), (0, 1, 1, 1), (0, 2, 1, 1), (0, 3, 2, 1), (2, 0, 1, 2), (2, 1, 2, 2), (2, 2, 1, 2), (2, 2, 2, 3), (2, 3, 2, 3)]
    assert [(g, e, b - a, t) for g, e, a, b, t in rows_of(d.deliver(pieces, "two_phase", pes=4))] == [
        (0, 0, 3, 0), (0, 1, 2, 1), (0, 2, 1, 0), (0, 3, 2, 1), (2, 0, 1, 2), (2, 1, 2, 2), (2, 2, 1, 2), (2, 2, 2, 3), (2, 3, 2, 3)]


@pytest.mark.parametrize("method", ["prefix", "permuted", "chunked", "two_phase"])
def test_every_word_is_delivered_once(spark, method):
    rng = random.Random(4)
    for p, r in ((8, 2), (16, 4), (12, 3)):
        data = [(e, j * p // r, rng.choice([0, 1, rng.randrange(200)]), j * p // r, p // r) for e in range(p) for j in range(r)]
        out = rows_of(d.deliver(spark.createDataFrame(data, "pe int, grp int, size long, base int, q int"), method, pes=p))
        loads = {}
        for e, g, s, base, q in data:
            at = 0
            for a, b, t in sorted((a, b, t) for gg, pe, a, b, t in out if (gg, pe) == (g, e)):
                assert a == at and base <= t < base + q
                at = b
                loads[t] = loads.get(t, 0) + b - a
            assert at == s
        total = {g: sum(s for _, gg, s, _, _ in data if gg == g) for g in {x[1] for x in data}}
        cap = max(-(-t // (p // r)) for t in total.values())
        assert max(loads.values()) <= cap


def test_tiny_pieces_flood_plain_delivery_only(spark):
    pieces = tiny_run(spark, 64, 4, 0, 60)
    got = {m: d.message_stats(d.deliver(pieces, m, pes=64)).first().max_recv for m in ("prefix", "chunked", "two_phase")}
    assert got["prefix"] >= 50 and got["two_phase"] <= 3 * 4 + 2 and got["chunked"] < got["prefix"]
    assert d.message_stats(d.deliver(few_large(spark, 32, 4), "two_phase", pes=32)).first().max_recv <= 14


def test_schedules(spark):
    cells = spark.createDataFrame([(i, j, 1) for i in range(4) for j in range(4)], "src int, dst int, words long")
    rows = d.one_factor_schedule(cells, 4).collect()
    assert len(rows) == 12 and all((r.src + r.dst) % 4 == r["round"] for r in rows)
    rng = random.Random(2)
    messages = [(i, j, rng.randrange(1, 9)) for i in range(4) for j in range(4) if i != j]
    plan = d.edge_colour_schedule(messages)
    sent = {}
    for t, s, e, w in plan:
        sent[s, e] = sent.get((s, e), 0) + w
    assert sent == {(s, e): w for s, e, w in messages}
    length = {}
    for t, s, e, w in plan:
        assert length.setdefault(t, w) == w
        assert sum(1 for u, a, b, _ in plan if u == t and a == s) == 1 == sum(1 for u, a, b, _ in plan if u == t and b == e)
    top = max([sum(w for a, _, w in messages if a == i) for i in range(4)] + [sum(w for _, b, w in messages if b == i) for i in range(4)])
    assert sum(length.values()) == top


def test_cost_shapes():
    assert costmodel.isoefficiency("splitter", 2 ** 15, 2) < 1e6 < costmodel.isoefficiency("single", 2 ** 15) < costmodel.isoefficiency("merge", 2 ** 15, 2)
    assert costmodel.startups([32768]) == 32767 and costmodel.startups([2048, 16]) == 2064 and costmodel.startups([64, 32, 16]) == 112
    assert costmodel.sample_size(0.01, 16) < costmodel.sample_size(0.01, 16, False)
    a = (1e-5, 1e-9)
    n = 10 ** 5 * 2 ** 15
    assert costmodel.splitter_sort(n, 2 ** 15, [64, 32, 16], 0.1, *a) < costmodel.splitter_sort(n, 2 ** 15, [2 ** 15], 0.1, *a)
    assert costmodel.merge_sort(n, 2 ** 15, [64, 32, 16], *a) > costmodel.splitter_sort(n, 2 ** 15, [64, 32, 16], 0.1, *a)


def test_curve_and_table_functions(spark):
    import numpy as np

    from tiersort.functions.udfs import hilbert, register

    g = np.arange(16)
    x, y = np.repeat(g, 16), np.tile(g, 16)
    at = hilbert(x, y, 4)
    order = np.argsort(at)
    assert sorted(at.tolist()) == list(range(256))
    assert (np.abs(np.diff(x[order])) + np.abs(np.diff(y[order])) == 1).all()  # neighbours on the curve touch
    register(spark, 4)
    assert [tuple(r) for r in spark.sql("select level, r from level_plan(512, 3, 'node')").collect()] == [(0, 8), (1, 4), (2, 16)]
    assert spark.sql("select count(*) from one_factor(4)").first()[0] == 12
    assert spark.sql("select hilbert_key(id, id) from range(3)").count() == 3


def test_arrow_classification_agrees(spark):
    from tiersort.operators.splitters import classify_arrow

    rows = spark.range(300).select((F.col("id") % 13).alias("x"), F.col("id"), (F.col("id") % 2).cast("int").alias("_ms_grp"))
    table = spark.createDataFrame([(0, [(2, 5), (2, 80), (2, 90), (7, 0), (12, 400)]), (1, [(5, 5)])], "grp int, splitters array<struct<k0:bigint,k1:bigint>>")
    by = key("x", ties=("id",))
    a, b = ({r.id: r.bucket for r in f(rows, table, by).collect()} for f in (classify, classify_arrow))
    assert a == b


def _never(*_):
    raise TimeoutError("the selection doesn't end")


@pytest.mark.parametrize("m", [1, 8])
def test_selection_among_equal_keys(spark, m):
    runs = spark.createDataFrame([(0, e, x, 7) for e in range(2) for x in range(10)], "_ms_grp int, _ms_pe int, _ms_pos long, x int")
    old = signal.signal(signal.SIGALRM, _never)
    signal.alarm(90)
    try:
        got = select_splits(runs, key("x"), {0: [0, 5, 13, 20]}, pivots_per_round=m)
    finally:
        signal.alarm(0)
        signal.signal(signal.SIGALRM, old)
    assert {k: tuple(c.values()) for (_, k), c in got.items()} == {0: (0, 0), 5: (5, 0), 13: (10, 3), 20: (10, 10)}


@pytest.mark.parametrize("merge", ["timsort", "arrow"])
def test_merges_of_repeated_rows(spark, merge):
    df = spark.createDataFrame([(1, "a")] * 150 + [(i % 3, "b") for i in range(90)], "x int, y string")
    old = signal.signal(signal.SIGALRM, _never)
    signal.alarm(120)
    try:
        layout = merge_sort(df, key("x"), 6, levels=[3, 2], merge=merge)
        rows = layout.df.select("_ms_pe", "x", "y").collect()
        runs = merge_runs(df.withColumn("run", F.when(F.col("y") == "a", 0).otherwise(1)), key("x"), 4).df.groupBy("_ms_pe").count().collect()
    finally:
        signal.alarm(0)
        signal.signal(signal.SIGALRM, old)
    parts = [[r.x for r in rows if r._ms_pe == pe] for pe in range(6)]
    assert [x for p in parts for x in p] == sorted(r.x for r in df.collect()) and [len(p) for p in parts] == [40] * 6
    assert sorted((r.x, r.y) for r in rows) == sorted(map(tuple, df.collect()))
    assert sorted(r["count"] for r in runs) == [60] * 4
