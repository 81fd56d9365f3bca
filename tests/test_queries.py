"""A part of the catalogue against its SQL, and invariants of the sorts."""

import math

import duckdb
import pytest
from pyspark.sql import functions as F

from tiersort.functions.keys import key
from tiersort.operators import baselines
from tiersort.operators.sort import merge_sort, splitter_sort
from tiersort.plans import catalog, studies
from tiersort.sources.sinks import read_sorted, write_sorted
from tiersort.sources.tables import rand64, rec100
from tiersort.streaming.runs import merge_runs, read_runs, stream_runs, windowed_counts

FOLDER = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = ["q02_mss_k2_price", "q08_mms_k2_price", "q13_sort_nulls", "q16_sort_two_keys", "q19_select_many", "q25_packing", "q26_slices_prefix", "q27_slices_two_phase", "q29_slices_chunked",
        "q46_g_rank", "q49_g_cume_dist", "q52_g_lag_lead", "q53_g_first_last", "q58_join_full", "q61_join_asof", "q63_dedupe_sort", "q83_late_split", "q84_run_merge"]


def norm(x):
    return "nan" if isinstance(x, float) and math.isnan(x) else str(x)


@pytest.mark.parametrize("name", SOME)
def test_query(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{FOLDER}/{t}.parquet'")
    got = con.execute(catalog.ORACLES[name])
    names = [c[0] for c in got.description]
    want = sorted(tuple(map(norm, r)) for r in got.fetchall())
    df = catalog.QUERIES[name](spark, FOLDER)
    assert sorted(df.columns) == sorted(names)
    assert sorted(tuple(map(norm, r)) for r in df.select(*names).collect()) == want


def values(layout, column):
    rows = [(r._ms_pe, r[column]) for r in layout.df.select("_ms_pe", column).collect()]
    by_pe = {}
    for pe, v in rows:
        by_pe.setdefault(pe, []).append(v)
    return [by_pe.get(pe, []) for pe in range(layout.p)]


@pytest.mark.parametrize("n", [0, 1, 3, 200])
@pytest.mark.parametrize("sort", [splitter_sort, merge_sort])
def test_small_inputs_and_odd_p(spark, sort, n):
    df = spark.createDataFrame([(i, (i * 7919) % 101) for i in range(n)], "id long, x long")
    layout = sort(df, key("x", ties=("id",)), 6, levels=[3, 2], by="id")
    parts = values(layout, "x")
    assert [v for p in parts for v in p] == sorted((i * 7919) % 101 for i in range(n))
    if sort is merge_sort:
        assert [len(p) for p in parts] == [n * (x + 1) // 6 - n * x // 6 for x in range(6)]
    layout.release()


def test_equal_keys_balance_only_with_ties(spark):
    df = spark.range(800).select("id", F.lit(5).alias("x"))
    with_ties = splitter_sort(df, key("x", ties=("id",)), 4, 1, by="id")
    without = splitter_sort(df, key("x"), 4, 1, by="id", ties="none")
    for mode in ("level", "origin"):
        assert max(map(len, values(splitter_sort(df, key("x"), 4, 2, ties=mode), "x"))) < 260
    assert max(map(len, values(with_ties, "x"))) < 260 and max(map(len, values(without, "x"))) == 800


def test_overpartitioning_balances_at_equal_sample(spark):
    df = rand64(spark, 20_000)
    by = key("key", ties=("id",))
    eps = [splitter_sort(df, by, 8, 1, a=a, b=b, by="id").load_stats().first().eps for a, b in ((8, 16), (128, 1))]
    assert eps[0] < 0.06 and eps[0] < eps[1]


def test_merge_of_arrow_runs_and_deliveries_agree(spark):
    df = rand64(spark, 3000).withColumn("x", F.when(F.col("id") % 9 == 0, None).when(F.col("id") % 13 == 0, float("nan")).otherwise((F.col("key") % 50).cast("double")))
    for by in (key("x", ties=("id",)), key("x", desc=("x",), nulls_first=("x",), ties=("id",))):
        want = [r.id for r in df.orderBy(*by.order()).collect()]
        for options in ({"merge": "arrow", "fan_in": 2, "delivery": "two_phase"}, {"delivery": "permuted", "pivots_per_round": 1}):
            assert [v for p in values(merge_sort(df, by, 4, 2, by="id", **options), "id") for v in p] == want


def test_types_without_order_are_refused(spark):
    df = spark.range(3).select("id", F.create_map(F.lit("a"), F.col("id")).alias("m"))
    with pytest.raises(TypeError):
        splitter_sort(df, key("m"), 2)


def test_baselines_sort(spark):
    df = rand64(spark, 500)
    by = key("key", ties=("id",))
    want = [r.key for r in df.orderBy("key").collect()]
    for f in (baselines.single_sample_sort, baselines.central_multilevel_sort, baselines.parallel_quicksort, baselines.parallel_mergesort, baselines.single_merge_sort):
        assert [v for p in values(f(df, by, 4, by="id"), "key") for v in p] == want, f.__name__


def test_records_written_and_read(spark, tmp_path):
    df = rec100(spark, 400)
    assert df.select(F.max(F.length("key") + F.length("payload"))).first()[0] == 100
    layout = splitter_sort(df, key("key", ties=("id",)), 4, 1, by="id")
    write_sorted(layout, f"{tmp_path}/t")
    again = read_sorted(spark, f"{tmp_path}/t", layout.key, 4)
    assert values(again, "id") == values(layout, "id")
    assert sum(map(len, values(layout.rebalance(3), "id"))) == 400


def test_streamed_runs_merge(spark, tmp_path):
    events = spark.read.parquet(f"{FOLDER}/events.parquet").select("event_id", "ts", "event_type")
    for i in range(3):
        events.where(F.col("event_id") % 3 == i).write.parquet(f"{tmp_path}/in/{i}")
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 2).parquet(f"{tmp_path}/in/*")
    q = stream_runs(stream, key("ts", ties=("event_id",)), f"{tmp_path}/runs", f"{tmp_path}/cp")
    q.awaitTermination(120)
    runs = read_runs(spark, f"{tmp_path}/runs")
    assert runs.count() == events.count()
    got = [v for p in values(merge_runs(runs, key("ts", ties=("event_id",)), 4), "event_id") for v in p]
    assert got == [r.event_id for r in events.orderBy("ts", "event_id").collect()]
    stamped = stream.withColumn("ts", F.col("ts").cast("timestamp"))
    q = windowed_counts(stamped, "ts", "1 hour", "100 days").writeStream.format("memory").queryName("counts").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert spark.sql("select sum(n) from counts").first()[0] == events.count()


def test_interval_overlap_of_whole_orders(spark):
    rows = [(r.o_orderkey, round(r.o_totalprice * 100), round(r.o_totalprice * 100) + r.o_custkey % 97) for r in spark.read.parquet(f"{FOLDER}/orders.parquet").collect()]
    want = sorted((a[0], b[0]) for a in rows for b in rows if a[1] < b[2] and b[1] < a[2] and a[2] > a[1] and b[2] > b[1])
    got = sorted(map(tuple, catalog.QUERIES["q62b_interval_overlap_whole"](spark, FOLDER).collect()))
    assert got == want and len({a for a, _ in got}) == sum(r[2] > r[1] for r in rows)
    test_query(spark, "q62b_interval_overlap_whole")


@pytest.mark.parametrize("name", ["q21_grid_square", "q59_theta_join", "q60_join_band"])
def test_all_pairs_queries(spark, name):
    test_query(spark, name)


@pytest.mark.parametrize("desc", [(), ("x",)])
def test_bands_in_one_value_and_across_pes(spark, desc):
    xs = [None, 5.0, *[7.0] * 300, *(i / 4 for i in range(-20, 60)), float("nan"), float("inf")]
    rows = spark.createDataFrame(list(enumerate(xs)), "id long, x double")
    asked = [(0, 7.0), (1, -0.1), (2, 100.0), (3, None), (4, -50.0), (5, 7.0), (6, float("nan"))]
    other = spark.createDataFrame(asked, "q long, t double")
    held = lambda t, x: t is not None and x is not None and t - 0.5 <= x <= t + 0.5
    want = {q: sum(held(t, x) for x in xs) + (q == 6) for q, t in asked}  # not-a-number equals itself
    for nulls in ((), ("x",)):
        layout = splitter_sort(rows, key("x", desc=desc, nulls_first=nulls, ties=("id",)), 6, 1)
        assert {r.q: r.n for r in layout.band_count(other, F.col("t") - 0.5, F.col("t") + 0.5).collect()} == want
        pairs = layout.band_join(other, "t", 0.5).groupBy("q").count().collect()
        assert {r.q: r["count"] for r in pairs} == {q: n for q, n in want.items() if n}
    whole = splitter_sort(spark.range(100).withColumn("x", F.col("id") % 10), key("x", ties=("id",)), 4, 1)
    assert [r.n for r in whole.band_count(other.where("q = 0"), F.col("t") - 0.5, F.col("t") + 1.5).collect()] == [20]
    assert whole.band_count(other.limit(0), F.col("t"), F.col("t")).count() == 0


def test_band_join_does_not_meet_all_of_a_pe(spark):
    layout = splitter_sort(spark.range(60_000).withColumn("x", F.col("id").cast("double")), key("x"), 2, 1)
    near = layout.band_join(spark.range(60_000).select(F.col("id").cast("double").alias("t")), "t", 1.0)
    assert "_ms_cell" in near._jdf.queryExecution().executedPlan().toString()
    assert near.count() == 3 * 60_000 - 2


def test_large_matrix_of_ranks(spark, monkeypatch):
    from tiersort.operators import splitters

    monkeypatch.setattr(splitters, "MOST_MATRIX", 50)
    rows = spark.createDataFrame([(i, (i * 37) % 50) for i in range(400)], "id int, x int")
    want = {i: k for k, (_, i) in enumerate(sorted(((i * 37) % 50, i) for i in range(400)))}
    assert {r.id: r["rank"] for r in splitters.grid_rank_matrix(rows, key("x", ties=("id",))).collect()} == want


MADE_OF_TABLES = ["q111_gossip_hypercube", "q111b_gossip_tree", "q118_plans", "q119_startups", "q120_rounds", "q32_one_factor", "q33_level_plans", "q91_level_plan_udtf"]


@pytest.mark.parametrize("name", MADE_OF_TABLES)
def test_plans_and_schedules_follow_the_orders(spark, name, tmp_path):
    """As their SQL, also where other years and PEs have most of the rows, and there is no order at all."""
    rows = spark.read.parquet(f"{FOLDER}/orders.parquet")
    few = rows.where("o_orderkey % 16 not in (3, 5)")
    more = few.where("year(o_orderdate) = 1995").crossJoin(spark.range(40).withColumnRenamed("id", "_i")).withColumn("o_orderkey", F.col("o_orderkey") + 16 * F.col("_i")).drop("_i")
    con = duckdb.connect()
    for folder, df in (("few", few), ("more", few.unionByName(more)), ("none", rows.limit(0))):
        df.write.parquet(f"{tmp_path}/{folder}/orders.parquet")
        con.execute(f"create or replace view orders as select * from '{tmp_path}/{folder}/orders.parquet/*.parquet'")
        got = con.execute({**catalog.ORACLES, **studies.ORACLES}[name])
        names = [c[0] for c in got.description]
        want = sorted(tuple(map(norm, r)) for r in got.fetchall())
        out = {**catalog.QUERIES, **studies.QUERIES}[name](spark, f"{tmp_path}/{folder}")
        assert sorted(out.columns) == sorted(names)
        assert sorted(tuple(map(norm, r)) for r in out.select(*names).collect()) == want
        assert want or folder == "none"


def test_predictions_follow_the_orders(spark):
    rows = studies.QUERIES["q121_comparisons"](spark, FOLDER).collect()
    years = {r.y: r.n for r in spark.read.parquet(f"{FOLDER}/orders.parquet").groupBy(F.year("o_orderdate").alias("y")).agg(F.count("*").alias("n")).collect()}
    assert {r.y: r.n for r in rows} == years and len(rows) == 3 * len(years)
    assert all(r.splitter > r.n / r.p and r.splitter_seconds > 0 for r in rows)


@pytest.mark.parametrize("name", ["q122c_slowdown", "q122d_fluctuation"])
def test_weak_scaling_of_a_table(spark, name, monkeypatch):
    ran, real = [], studies.workloads.splitter_sort
    monkeypatch.setattr(studies.workloads, "splitter_sort", lambda df, *a, **o: ran.append(sorted(r.id for r in df.collect())) or real(df, *a, **o))
    got = studies.QUERIES[name](spark, FOLDER).collect()
    ids = sorted(r.c_custkey for r in spark.read.parquet(f"{FOLDER}/customer.parquet").select("c_custkey").collect())
    per = -(-len(ids) // 8)
    assert len(ran) == 20 and all(x in (ids, ids[:4 * per]) for x in ran) and ran.count(ids) == 10
    assert {(r.p, r.per_pe) for r in got} == {(4, per), (8, per)}
