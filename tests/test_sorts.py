"""The sorts as a whole: nothing lost, balance, plans, forms that must agree; and the array functions under them."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from tiersort.functions import costmodel as cost
from tiersort.functions.dealing import Dealing, traffic
from tiersort.functions.keys import key
from tiersort.functions.search import lex_order, lex_search
from tiersort.operators import delivery as d
from tiersort.operators.layout import equi_width
from tiersort.operators.merging import merged_order
from tiersort.operators.selection import select_keys
from tiersort.operators.sort import merge_sort, numbered, place, splitter_sort
from tiersort.sources.sinks import measure_only, write_bucketed, write_metrics
from tiersort.sources.tables import rand64, rate_keys
from tiersort.streaming.runs import distinct_within, in_order, split_late

FOLDER = "/root/testdata/sf0.001"


def ids(layout):
    return [r.id for r in layout.with_rank().orderBy("rank").select("id").collect()]


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(i, None if i % 10 == 0 else -i if i % 3 else i % 5, (i * 7919) % 211) for i in range(1000)]
    return spark.createDataFrame(rows, "id long, b long, x long")


@pytest.mark.parametrize("sort", [splitter_sort, merge_sort])
@pytest.mark.parametrize("placement", ["hash", "skew"])
def test_null_negative_and_repeated_placement_columns(odd, sort, placement):
    layout = sort(odd, key("x", ties=("id",)), 8, 2, by="b", placement=placement)
    assert ids(layout) == [r.id for r in odd.orderBy("x", "id").collect()]
    assert max(layout.loads) * 8 / 1000 - 1 < 0.2 and sum(layout.loads) == 1000
    assert place(odd, 8, "hash", "b").count() == 1000


def test_forms_deliveries_and_tie_modes_agree(spark):
    df = spark.read.parquet(f"{FOLDER}/events.parquet").select(F.col("event_id").alias("id"), "event_type", "value").withColumn("value", F.when(F.col("id") % 50 == 0, None).otherwise(F.col("value")))
    by = key("event_type", "value", desc=("value",), ties=("id",))
    want = [r.id for r in df.orderBy(*by.order()).collect()]
    for options in ({"form": "staged"}, {"ties": "origin", "reuse": True}, {"ties": "none", "delivery": "chunked"}, {"sample_sort": "grid", "delivery": "permuted", "capacity": "bound"}):
        assert ids(splitter_sort(df, by, 6, levels=[3, 2], **options)) == want, options


def test_origin_ties_balance_and_repeat(spark):
    df = spark.read.parquet(f"{FOLDER}/lineitem.parquet").select("l_discount", "l_orderkey", "l_extendedprice")
    runs = []
    for _ in range(2):
        layout = splitter_sort(df, key("l_discount"), 8, 2, ties="origin", eps=0.2)
        assert max(layout.loads) * 8 / sum(layout.loads) - 1 <= 0.2
        runs.append(sorted(map(tuple, layout.with_rank().select("rank", "l_orderkey", "l_extendedprice").collect())))
    assert runs[0] == runs[1]


def test_plans_grow_by_the_same_with_each_level(spark):
    df = spark.read.parquet(f"{FOLDER}/orders.parquet").select("o_orderkey", "o_totalprice")
    by = key("o_totalprice", ties=("o_orderkey",))
    for levels in ([8], [4, 2], [2, 2, 2]):
        for layout in (splitter_sort(df, by, 8, levels=levels), merge_sort(df, by, 8, levels=levels)):
            assert layout.explain_plan().count("\n(") < 12 and layout.df._jdf.queryExecution().executedPlan().toString().count("Exchange") == 1
        report = splitter_sort(df, by, 8, levels=levels).report
        assert sum(r.get("moves", 0) for r in report.rows) == len(levels)


def test_inputs_of_many_files_and_no_files(spark, tmp_path):
    df = rand64(spark, 500).repartition(7)
    df.write.parquet(f"{tmp_path}/many")
    df.write.csv(f"{tmp_path}/csv")
    by = key("key", ties=("id",))
    want = [r.id for r in df.orderBy("key").collect()]
    many, csv = spark.read.parquet(f"{tmp_path}/many"), spark.read.schema("id long, key long").csv(f"{tmp_path}/csv")
    rows, total, n = numbered(many)
    assert (total, n) == (500, 500) and sorted(r._ms_id for r in rows.collect()) == list(range(500))
    for x in (many, csv, many.join(csv, ["id", "key"]), many.withColumn("again", F.rand())):
        assert ids(splitter_sort(x, by, 4, 2)) == want


def test_views_and_bucketed_tables(spark, tmp_path):
    layout = merge_sort(rand64(spark, 300), key("key"), 4, 2)
    assert layout.views() == ["ms_loads", "ms_report"]
    assert spark.sql("select sum(cnt) from ms_loads").first()[0] == 300
    assert spark.sql("select sum(value) from ms_report where metric = 'moves'").first()[0] == 2
    write_bucketed(layout, "sorted_keys", 4)
    assert spark.table("sorted_keys").count() == 300
    spark.sql("drop table sorted_keys")
    for _ in range(2):
        write_metrics(layout.report.table(spark), f"{tmp_path}/metrics")
    assert spark.read.json(f"{tmp_path}/metrics").count() == 2 * layout.report.table(spark).count()
    assert rate_keys(spark).isStreaming
    assert {r.bucket: r.n for r in equi_width(spark.range(-1, 12), "id", 0.0, 10.0, 5).collect()} == {0: 1, 1: 2, 2: 2, 3: 2, 4: 2, 5: 2, 6: 2}


def test_later_rounds_read_fewer_rows(spark):
    rows, _, n = numbered(rand64(spark, 20_000))
    stats: dict = {}
    keys, cuts = select_keys(rows, key("key"), {0: [1, 7_000, 20_000]}, {0: n}, F.lit(0).cast("long"), ("_ms_id",), most_collect=300, stats=stats)
    want = sorted(r.key for r in rows.collect())
    assert [int(keys.values[0][cuts[0, k]]) for k in (1, 7_000, 20_000)] == [want[0], want[6_999], want[-1]]
    assert stats["rows_read"][1] < 0.2 * stats["rows_read"][0] and stats["rounds"] < 8


# ---- arrays

def plain_key(row, ways):
    return tuple((x if w else tuple(-ord(c) for c in x) + (1,) if isinstance(x, str) else -x) for x, w in zip(row, ways))


def test_search_and_merge_against_sorting():
    rng = random.Random(1)
    for ways in ([True, True, True], [False, True, False], [True, False, True]):
        rows = [(rng.randrange(3), rng.choice("abc"), rng.random() if rng.random() < 0.5 else 0.5) for _ in range(300)]
        table = sorted(rng.sample(rows, 40), key=lambda r: plain_key(r, ways))
        arrays = lambda x: [np.array([r[0] for r in x]), np.array([r[1] for r in x], object), np.array([r[2] for r in x])]
        names = [plain_key(r, ways) for r in table]
        for right in (False, True):
            got = lex_search(arrays(rows), arrays(table), ways, right)
            assert got.tolist() == [sum(t <= plain_key(r, ways) if right else t < plain_key(r, ways) for t in names) for r in rows]
        order = lex_order(arrays(rows), ways)
        assert [plain_key(rows[i], ways) for i in order] == sorted(plain_key(r, ways) for r in rows)
        stretches = [np.array(sorted(range(x, 300, 9), key=lambda i: plain_key(rows[i], ways))) for x in range(9)]
        for fan_in, passes in ((2, 4), (3, 2), (64, 1)):
            order, n = merged_order(arrays(rows), ways, list(stretches), fan_in)
            assert n == passes and sorted(order.tolist()) == list(range(300))
            assert [plain_key(rows[i], ways) for i in order] == sorted(plain_key(r, ways) for r in rows)


@pytest.mark.parametrize("method, capacity", [("prefix", "even"), ("prefix", "bound"), ("permuted", "even"), ("chunked", "even"), ("two_phase", "even")])
def test_dealing_equals_slices(spark, method, capacity):
    rng = random.Random(7)
    p, r = 12, 3
    sizes = np.array([[rng.choice([0, 1, 2, 30, 90]) for _ in range(r)] for _ in range(p)])
    base, q = [0, 4, 8], [4, 4, 4]
    pieces = spark.createDataFrame([(i, base[j], int(sizes[i, j]), base[j], q[j]) for i in range(p) for j in range(r)], "pe int, grp int, size long, base int, q int")
    want = {}
    for s in d.deliver(pieces, method, capacity, 1, p).collect():
        for x in range(s.from_pos, s.to_pos):
            want[s.pe, base.index(s.grp), x] = s.target
    dealing = Dealing(sizes, base, q, method, capacity, 1)
    src, grp, x = (np.array(v) for v in zip(*want))
    assert dealing.at(src, grp, x).tolist() == list(want.values()) and len(want) == sizes.sum()


@pytest.mark.parametrize("p, r", [(8, 2), (16, 4), (64, 8), (96, 6)])
def test_two_phase_bounds_messages(p, r):
    for seed in range(6):
        rng = np.random.default_rng(seed)
        share = rng.dirichlet([0.15] * r, p)
        sizes = np.array([rng.multinomial(1000, w) for w in share])
        q = [(j + 1) * p // r - j * p // r for j in range(r)]
        dealing = Dealing(sizes, [j * p // r for j in range(r)], q, "two_phase")
        src, grp = (np.repeat(i.reshape(-1), sizes.reshape(-1)) for i in np.indices(sizes.shape))
        x = np.concatenate([np.arange(n) for n in sizes.reshape(-1)])
        target = dealing.at(src, grp, x)
        load = np.bincount(target, minlength=p)
        assert load.max() <= dealing.cap.max()
        stats = traffic(src, target, np.ones(len(src)))
        assert stats["max_recv"] <= 3 * r + 2


def test_costs_are_fitted():
    rows = [(m, w, 2e-3 * m + 5e-6 * w) for m, w in ((10, 1000), (50, 400), (7, 9000))]
    alpha, beta = cost.fit(rows)
    assert abs(alpha - 2e-3) < 1e-9 and abs(beta - 5e-6) < 1e-12
    assert min(cost.fit([(1, 10, 1.0), (2, 10, 0.5)])) >= 0


# ---- streams

def test_late_rows_stand_aside_and_others_come_in_order(spark, tmp_path):
    events = spark.read.parquet(f"{FOLDER}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "event_type").orderBy("ts").limit(300)
    cuts = events.approxQuantile("event_id", [0.5], 0.0)[0]
    events.where(F.col("event_id") > cuts).write.parquet(f"{tmp_path}/in/0")
    events.where(F.col("event_id") <= cuts).write.parquet(f"{tmp_path}/in/1")
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*")
    split_late(stream, "ts", "1 minute", f"{tmp_path}/out", f"{tmp_path}/cp").awaitTermination(120)
    late = spark.read.option("basePath", f"{tmp_path}/out/late").parquet(f"{tmp_path}/out/late")
    fine = spark.read.option("basePath", f"{tmp_path}/out/rows").parquet(f"{tmp_path}/out/rows")
    assert late.count() > 0 and late.count() + fine.count() == 300
    q = distinct_within(stream, "ts", ["event_type"], "1000 days").writeStream.format("memory").queryName("firsts").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert spark.sql("select count(*) from firsts").first()[0] == events.select("event_type").distinct().count()
    q = in_order(stream, "event_type", "ts", "event_id", "1 second").writeStream.format("memory").queryName("ordered").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    rows = spark.sql("select * from ordered order by event_type, place").collect()
    for kind in {r.event_type for r in rows}:
        mine = [r for r in rows if r.event_type == kind]
        assert [r.place for r in mine] == list(range(len(mine)))
    assert rows


def test_measured_phases_cover_the_sort(spark):
    report = splitter_sort(rand64(spark, 2000), key("key"), 4, 2, measure=True).report
    assert {r["phase"] for r in report.rows} == {"splitter selection", "bucket processing", "data delivery", "local sort"}
    assert all(r["seconds"] >= 0 for r in report.rows)
    measure_only(report.table(spark))


def test_workers_need_not_have_the_package(spark, tmp_path):
    """What goes to the workers loads and runs where the package can't be imported."""
    import subprocess
    import sys

    from pyspark import cloudpickle
    from tiersort.functions.routing import Router, runs_below
    from tiersort.functions.search import Codes

    df = spark.createDataFrame([(1, "a", 2.0)], "i long, s string, x double")
    codes = Codes(df, key("s", "x"), ("i",))
    values = [np.array(["b", "c"], object), np.array([1.0, 2.0]), np.array([0, 0])]
    router = Router(codes, 3, np.zeros(2, np.int64), np.zeros(2, np.int64), values, [0])
    dealing = Dealing(np.array([[3, 2], [1, 4]]), [0, 1], [1, 1], "permuted")
    (tmp_path / "sent").write_bytes(cloudpickle.dumps((router, dealing, runs_below(router, True))))
    code = """
import pickle, numpy as np, pandas as pd
try:
    import tiersort
    raise SystemExit("the package is here")
except ImportError:
    pass
router, dealing, count = pickle.load(open("sent", "rb"))
g, at = router.bounds_below(np.array([0, 0]), [pd.Series([0, 0]), pd.Series(["a", "d"], dtype=object), pd.Series([0.0, 0.0]), pd.Series([1, 2])])
assert at.tolist() == [0, 2], at
assert dealing.at(np.array([0, 1]), np.array([0, 1]), np.array([0, 3])).tolist() == [0, 1]
assert list(count(iter([]))) == []
"""
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, env={"PATH": "/usr/bin"}, timeout=100)
    assert done.returncode == 0, done.stderr
