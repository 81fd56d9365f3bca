"""All queries of the engine and their SQL.

Sorted results carry ``rank`` (from 0) or ``pe`` as data. Splitter choices are
replayed in SQL through the same integer hash.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tiersort.functions.keys import KeySpec, key
from tiersort.functions.mixing import morton_key, quantised
from tiersort.operators import baselines as base
from tiersort.operators import delivery as d
from tiersort.operators.layout import SortedLayout, interval_join, set_op
from tiersort.operators.packing import packing_table
from tiersort.operators.selection import at_ranks, select_splits
from tiersort.operators.sort import merge_sort, numbered, splitter_sort
from tiersort.operators.splitters import bucket_sizes, choose_splitters, classify, draw_sample, grid_rank, grid_rank_matrix, sort_sample
from tiersort.plans.topology import plan_levels
from tiersort.sources.tables import pieces_of, read_table

QUERIES: dict = {}
ORACLES: dict = {}
P = 8
LINE_TIES = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")
LINE = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice"]
PRICE = key("l_extendedprice", ties=LINE_TIES)
TOTAL = key("o_totalprice", ties=("o_orderkey",))
TS = key("ts", ties=("event_id",))


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f
    return add


def flagship(spark: SparkSession, folder: str) -> DataFrame:
    layout = splitter_sort(read_table(spark, folder, "lineitem", LINE), PRICE, 16, 2, by="l_orderkey")
    return layout.with_rank().select("rank", F.col("_ms_pe").alias("pe"), *LINE)


# ---- sorts

def _ranked(layout: SortedLayout, *columns: str) -> DataFrame:
    return layout.with_rank().select("rank", *columns)


def _sort_query(name: str, table: str, columns: list[str], by: KeySpec, order: str, how, with_pe: bool = False, source: str | None = None) -> None:
    def run(spark, folder):
        layout = how(read_table(spark, folder, table, columns))
        out = layout.with_rank()
        return out.select("rank", *columns, *([F.col("_ms_pe").alias("pe")] if with_pe else []))
    QUERIES[name] = run
    listed = ", ".join(columns)
    number = f"(row_number() over (order by {order}) - 1)::bigint"
    pe = f", (((({number}) + 1) * {P} - 1) // (select count(*) from {table}))::int as pe" if with_pe else ""
    ORACLES[name] = f"select {number} as rank, {listed}{pe} from {table}"


def _mss(by, k=2, levels=None, p=P, col=None, **more):
    return lambda df: splitter_sort(df, by, p, k, levels=levels, by=col, **more)


def _mms(by, k=2, levels=None, col=None, **more):
    return lambda df: merge_sort(df, by, P, k, levels=levels, by=col, **more)


_PO = "l_extendedprice, l_orderkey, l_partkey, l_suppkey, l_linenumber"
_sort_query("q01_mss_k1_price", "lineitem", LINE, PRICE, _PO, _mss(PRICE, 1, col="l_orderkey"))
_sort_query("q02_mss_k2_price", "lineitem", LINE, PRICE, _PO, _mss(PRICE, 2, col="l_orderkey"))
_sort_query("q03_mss_k3_price", "lineitem", LINE, PRICE, _PO, _mss(PRICE, levels=[2, 2, 2], col="l_orderkey"))
_OC = ["o_orderkey", "o_totalprice"]
_sort_query("q04_mss_k2_total", "orders", _OC, TOTAL, "o_totalprice, o_orderkey", _mss(TOTAL, 2, col="o_orderkey"))
_sort_query("q05_mss_sorted_input", "events", ["event_id", "ts"], TS, "ts, event_id", _mss(TS, 2, col="event_id", placement="block"))
_TD = key("ts", desc=("ts",), ties=("event_id",))
_sort_query("q06_mss_reverse", "events", ["event_id", "ts"], _TD, "ts desc, event_id", _mss(_TD, 2, col="event_id"))
_sort_query("q07_mms_k1_price", "lineitem", LINE, PRICE, _PO, _mms(PRICE, 1, col="l_orderkey"), True)
_sort_query("q08_mms_k2_price", "lineitem", LINE, PRICE, _PO, _mms(PRICE, 2, col="l_orderkey"), True)
_sort_query("q09_mms_k3_price", "lineitem", LINE, PRICE, _PO, _mms(PRICE, levels=[2, 2, 2], col="l_orderkey"), True)
_sort_query("q10_mms_k2_total", "orders", _OC, TOTAL, "o_totalprice, o_orderkey", _mms(TOTAL, 2, col="o_orderkey"), True)
_sort_query("q11_mms_k2_ts", "events", ["event_id", "ts"], TS, "ts, event_id", _mms(TS, 2, col="event_id", placement="block", merge="arrow"), True)
_sort_query("q14_sort_string", "customer", ["c_custkey", "c_name"], key("c_name", ties=("c_custkey",)), "c_name, c_custkey", _mss(key("c_name", ties=("c_custkey",)), 2, col="c_custkey"))
_sort_query("q14b_sort_string_ties", "part", ["p_partkey", "p_name"], key("p_name", ties=("p_partkey",)), "p_name, p_partkey", _mss(key("p_name", ties=("p_partkey",)), 2, col="p_partkey"))
_sort_query("q15_sort_timestamp", "orders", ["o_orderkey", "o_orderdate"], key("o_orderdate", ties=("o_orderkey",)), "o_orderdate, o_orderkey", _mss(key("o_orderdate", ties=("o_orderkey",)), 2, col="o_orderkey"))
_SP = key("o_orderpriority", "o_totalprice", desc=("o_totalprice",), ties=("o_orderkey",))
_sort_query("q16_sort_two_keys", "orders", ["o_orderkey", "o_orderpriority", "o_totalprice"], _SP, "o_orderpriority, o_totalprice desc, o_orderkey", _mss(_SP, 2, col="o_orderkey"))
_DI = key("l_discount", ties=(*LINE_TIES, "l_extendedprice"))
_sort_query("q17_sort_dups", "lineitem", [*LINE, "l_discount"], _DI, f"l_discount, {_PO.split(', ', 1)[1]}, l_extendedprice", _mss(_DI, 2, col="l_orderkey"))
for _name, _how in {"q34_b1_sample_sort": base.single_sample_sort, "q36_b3_central": base.central_multilevel_sort, "q37_b5a_quicksort": base.parallel_quicksort}.items():
    _sort_query(_name, "orders", _OC, TOTAL, "o_totalprice, o_orderkey", lambda df, f=_how: f(df, TOTAL, P, by="o_orderkey"))
for _name, _how in {"q35_b2_merge_sort_single": base.single_merge_sort, "q38_b5b_mergesort": base.parallel_mergesort, "q38b_b4_merge_every_level": base.merge_every_level_sort,
                    "q39_b6_resort": lambda df, k, p, **o: base.single_merge_sort(df, k, p, "resort", **o)}.items():
    _sort_query(_name, "orders", _OC, TOTAL, "o_totalprice, o_orderkey", lambda df, f=_how: f(df, TOTAL, P, by="o_orderkey"), True)
_sort_query("q40_b12_spark_sort", "orders", _OC, TOTAL, "o_totalprice, o_orderkey", lambda df: base.spark_sort(df, TOTAL, P))


@query("""select pe, count(*)::bigint as cnt, min(o_totalprice) as first, max(o_totalprice) as last from
(select o_totalprice, ((row_number() over (order by o_totalprice, o_orderkey) * 8 - 1) // (select count(*) from orders))::int as pe from orders) group by pe""")
def q12_mms_loads(spark, folder):
    layout = merge_sort(read_table(spark, folder, "orders", _OC), TOTAL, P, 2, by="o_orderkey")
    return layout.df.groupBy(F.col("_ms_pe").alias("pe")).agg(F.count("*").alias("cnt"), F.min("o_totalprice").alias("first"), F.max("o_totalprice").alias("last"))


@query("""select (row_number() over (order by b desc nulls last, c_custkey) - 1)::bigint as rank, c_custkey, b from
(select c_custkey, case when c_custkey % 7 = 0 then null when c_custkey % 11 = 0 then 'nan'::double else c_acctbal end as b from customer)""")
def q13_sort_nulls(spark, folder):
    b = F.when(F.col("c_custkey") % 7 == 0, None).when(F.col("c_custkey") % 11 == 0, float("nan")).otherwise(F.col("c_acctbal"))
    df = read_table(spark, folder, "customer").select("c_custkey", b.alias("b"))
    return _ranked(splitter_sort(df, key("b", desc=("b",), ties=("c_custkey",)), P, 2, by="c_custkey"), "c_custkey", "b")


# ---- building blocks

def _runs(spark, folder, runs: int = 8) -> DataFrame:
    df = read_table(spark, folder, "orders", _OC).withColumn("_ms_pe", (F.col("o_orderkey") % runs).cast("int")).withColumn("_ms_grp", F.lit(0))
    return df.withColumn("_ms_pos", F.row_number().over(Window.partitionBy("_ms_pe").orderBy(*TOTAL.order())).cast("long") - 1).persist()


_NUMBERED = "(select o_orderkey, o_totalprice, (o_orderkey % 8)::int as pe, row_number() over (order by o_totalprice, o_orderkey) as rn, (select count(*) from orders) as n from orders)"


@query(f"select pe, count(*) filter (where rn <= n // 2)::bigint as pos from {_NUMBERED} group by pe")
def q18_select_one(spark, folder):
    runs = _runs(spark, folder)
    k = runs.count() // 2
    got = select_splits(runs, TOTAL, {0: [k]}, pivots_per_round=1, most_collect=500)
    return spark.createDataFrame([(e, x) for e, x in got[0, k].items()], "pe int, pos long")


@query(f"select i.i::int as part, pe, count(*) filter (where rn <= i.i * n // 16)::bigint as pos from {_NUMBERED}, (select unnest(generate_series(1, 15)) as i) i group by i.i, pe")
def q19_select_many(spark, folder):
    runs = _runs(spark, folder)
    n = runs.count()
    got = select_splits(runs, TOTAL, {0: [i * n // 16 for i in range(1, 16)]})
    return spark.createDataFrame([(i, e, x) for i in range(1, 16) for e, x in got[0, i * n // 16].items()], "part int, pe int, pos long")


def _at_ranks(df: DataFrame, by: KeySpec, ranks: list[int]) -> DataFrame:
    """Keys at ranks (from 0), selected without sorting the table."""
    rows, _, n = numbered(df)
    return at_ranks(rows, by, ranks, ("_ms_id",), n)


@query("select (rn - 1)::bigint as at, l_extendedprice from (select l_extendedprice, row_number() over (order by " + _PO + ") as rn, count(*) over () as n from lineitem) where (rn - 1) in (select unnest([n * 1 // 4, n // 2, n * 3 // 4]))")
def q20_select_keys(spark, folder):
    df = read_table(spark, folder, "lineitem", LINE)
    n = df.count()
    return _at_ranks(df, PRICE, [n // 4, n // 2, 3 * n // 4]).select("at", "l_extendedprice")


@query("select s_suppkey, (row_number() over (order by s_acctbal, s_suppkey) - 1)::bigint as rank from supplier")
def q21_grid_square(spark, folder):
    return grid_rank_matrix(read_table(spark, folder, "supplier"), key("s_acctbal", ties=("s_suppkey",))).select("s_suppkey", "rank")


@query("select p_partkey, (row_number() over (order by p_retailprice, p_partkey) - 1)::bigint as rank from part")
def q22_grid_rect(spark, folder):
    return grid_rank(read_table(spark, folder, "part", ["p_partkey", "p_retailprice"]), key("p_retailprice", ties=("p_partkey",)), 8).select("p_partkey", "rank")


_SAMPLE = """s as (select *, row_number() over (order by o_totalprice, o_orderkey) as rank, count(*) over () as m from
 (select o_orderkey, o_totalprice from orders order by (o_orderkey % 2147483647 + 1) * 1103515245 % 2147483647, o_orderkey limit 256)),
sp as (select i, o_totalprice as price, o_orderkey as ok from s, (select unnest(generate_series(1, 31)) as i) where rank = (i * m + 31) // 32),
b as (select o.o_orderkey, count(sp.i)::int as bucket from orders o left join sp on (o.o_totalprice > sp.price or (o.o_totalprice = sp.price and o.o_orderkey > sp.ok)) group by o.o_orderkey)"""


def _splitters(spark, folder) -> tuple[DataFrame, DataFrame]:
    df = read_table(spark, folder, "orders", _OC).withColumn("_ms_grp", F.lit(0))
    sample = draw_sample(df, 256, "o_orderkey", df.count())
    return df, choose_splitters(sort_sample(sample, TOTAL, "_ms_grp"), TOTAL, "_ms_grp", 32)


@query(f"with {_SAMPLE} select i::int as i, price, ok from sp")
def q23_splitters(spark, folder):
    return _splitters(spark, folder)[1].select(F.posexplode("splitters").alias("i", "s")).select((F.col("i") + 1).cast("int").alias("i"), F.col("s.k0").alias("price"), F.col("s.k1").alias("ok"))


@query(f"with {_SAMPLE} select bucket, count(*)::bigint as size from b group by bucket")
def q24_bucket_sizes(spark, folder):
    df, splitters = _splitters(spark, folder)
    return bucket_sizes(classify(df, splitters, TOTAL)).select("bucket", "size")


_PACK = _SAMPLE.replace("with ", "") + """, z as (select bucket, count(*)::bigint as size from b group by bucket),
cum as (select bucket, sum(size) over (order by bucket) as s from z),
lim as (select distinct a.s - o.s as l from cum a, (select s from cum union all select 0) o where a.s > o.s),
c as (select l::bigint as l from lim where l >= (select max(size) from z)),
walk as (select l, 0 as bucket, 0 as part, (select size from z where bucket = 0) as load from c union all
 select w.l, w.bucket + 1, case when w.load + z.size > w.l then w.part + 1 else w.part end, case when w.load + z.size > w.l then z.size else w.load + z.size end from walk w join z on z.bucket = w.bucket + 1),
best as (select min(l) as l from (select l, max(part) as top from walk group by l) where top < 4)"""


@query(f"with recursive {_PACK} select bucket::int as bucket, part::int as part, walk.l as load_limit from walk join best on walk.l = best.l")
def q25_packing(spark, folder):
    df, splitters = _splitters(spark, folder)
    return packing_table(bucket_sizes(classify(df, splitters, TOTAL)), 4).select("bucket", "part", "load_limit")


# pieces: PE by order key, group by price quarter of the range
_PIECES = """pc as (select (o_orderkey % 16)::int as pe, least(3, floor(o_totalprice / 110000)::int) as g, count(*)::bigint as size from orders group by 1, 2),
pg as (select pe, g * 4 as grp, g * 4 as base, 4 as q, size, (sum(size) over (partition by g))::bigint as m from pc)"""


def _orders_pieces(spark, folder) -> DataFrame:
    grp = F.least(F.lit(3), F.floor(F.col("o_totalprice") / 110000))
    return pieces_of(read_table(spark, folder, "orders", _OC), 16, 4, F.col("o_orderkey") % 16, grp)


def _cut_sql(order: str) -> str:
    return f"""with {_PIECES}, st as (select *, coalesce(sum(size) over (partition by grp order by {order} rows between unbounded preceding and 1 preceding), 0)::bigint as start from pg),
x as (select *, unnest(generate_series(start * q // m, (start + size - 1) * q // m)) as t from st)
select grp, pe, (greatest((t * m + q - 1) // q, start) - start)::bigint as from_pos, (least(((t + 1) * m + q - 1) // q, start + size) - start)::bigint as to_pos, (base + t)::int as target from x"""


def _slices(out: DataFrame) -> DataFrame:
    return out.select("grp", "pe", F.col("from_pos").cast("long"), F.col("to_pos").cast("long"), F.col("target").cast("int"))


@query(_cut_sql("pe"))
def q26_slices_prefix(spark, folder):
    return _slices(d.deliver(_orders_pieces(spark, folder), "prefix"))


@query(f"""with {_PIECES}, f as (select *, sum(size) over () as n, (select max(ceil(m / q))::bigint from pg) as cap from pg),
sm as (select *, least(3, (count(*) over (partition by grp order by pe rows between unbounded preceding and 1 preceding) * 4) // 16) as t from f where size * 2 * 16 * 4 <= n),
rm as (select g.grp, g.t, g.cap - coalesce(w.given, 0) as free from (select distinct grp, cap, unnest([0, 1, 2, 3]) as t from f) g left join (select grp, t, sum(size) as given from sm group by all) w on g.grp = w.grp and g.t = w.t),
rx as (select *, coalesce(sum(free) over (partition by grp order by t rows between unbounded preceding and 1 preceding), 0) as x from rm),
ly as (select *, coalesce(sum(size) over (partition by grp order by pe rows between unbounded preceding and 1 preceding), 0) as y from f where size * 2 * 16 * 4 > n)
select grp, pe, 0::bigint as from_pos, size as to_pos, (base + t)::int as target from sm union all
select ly.grp, pe, (greatest(x, y) - y)::bigint, (least(x + free, y + size) - y)::bigint, (base + t)::int from ly join rx on ly.grp = rx.grp and x < y + size and y < x + free""")
def q27_slices_two_phase(spark, folder):
    return _slices(d.deliver(_orders_pieces(spark, folder), "two_phase", pes=16))


@query(_cut_sql("(pe::bigint * 7919 + grp * 104729 + 1) * 48271 % 2147483647, pe"))
def q28_slices_permuted(spark, folder):
    return _slices(d.deliver(_orders_pieces(spark, folder), "permuted", seed=1))


@query(f"""with {_PIECES}, ch as (select *, greatest(1, (ceil(m / q)::bigint) // (2 * q)) as chunk from pg),
cc as (select *, unnest(generate_series(0, (size - 1) // chunk)) as c from ch),
cd as (select grp, pe, base, q, m, c, c * chunk as lead, least(chunk, size - c * chunk) as size from cc),
st as (select *, coalesce(sum(size) over (partition by grp order by ((pe::bigint * 4096 + c) * 7919 + grp * 104729 + 1) * 48271 % 2147483647, pe, c rows between unbounded preceding and 1 preceding), 0)::bigint as start from cd),
x as (select *, unnest(generate_series(start * q // m, (start + size - 1) * q // m)) as t from st),
sl as (select grp, pe, greatest((t * m + q - 1) // q, start) - start + lead as a, least(((t + 1) * m + q - 1) // q, start + size) - start + lead as b, base + t as target from x),
fr as (select *, case when lag(b) over (partition by grp, pe, target order by a) = a then 0 else 1 end as fresh from sl where b > a),
rn as (select *, sum(fresh) over (partition by grp, pe, target order by a) as run from fr)
select grp, pe, min(a)::bigint as from_pos, max(b)::bigint as to_pos, target::int as target from rn group by grp, pe, target, run""")
def q29_slices_chunked(spark, folder):
    return _slices(d.deliver(_orders_pieces(spark, folder), "chunked", seed=1))


@query("select ((s + t) % 8)::int as round, s::int as src, t::int as dst, count(*)::bigint as words from (select o_orderkey % 8 as s, o_custkey % 8 as t from orders) where s <> t group by s, t")
def q32_one_factor(spark, folder):
    """Rounds in which orders, dealt by their own key, go to their customer's PE."""
    src, dst = ((F.col(c) % 8).cast("int") for c in ("o_orderkey", "o_custkey"))
    cell = read_table(spark, folder, "orders", ["o_orderkey", "o_custkey"]).groupBy(src.alias("src"), dst.alias("dst")).agg(F.count("*").alias("words"))
    return d.one_factor_schedule(cell, 8)


#: CTEs: a year's orders and the machine for them (m: y, n, p, bits), and its plans of one to three levels (plans: y, n, p, k, level, r).
MACHINES_SQL = """yr as (select year(o_orderdate)::int as y, count(*)::bigint as n from orders group by 1),
m as (select *, (16 << bits)::int as p from (select *, greatest(2, case when n > 1024 then length(bin((n - 1) // 1024)) else 0 end)::int as bits from yr)),
plans as (select y, n, p, k::int as k, level::int as level, r::int as r from (select y, n, p, 1 as k, 0 as level, p as r from m
 union all select y, n, p, 2, 0, 1 << bits from m union all select y, n, p, 2, 1, 16 from m
 union all select y, n, p, 3, 0, 1 << ((bits + 1) // 2) from m union all select y, n, p, 3, 1, 1 << (bits // 2) from m union all select y, n, p, 3, 2, 16 from m))"""


def yearly(spark, folder) -> DataFrame:
    """Rows (y, n, p): the orders of a year and the PEs of a machine for them, four nodes of 16 or the next power of two whose PEs hold 64 rows at most."""
    years = read_table(spark, folder, "orders", ["o_orderdate"]).groupBy(F.year("o_orderdate").alias("y")).agg(F.count("*").alias("n"))
    bits = F.when(F.col("n") > 1024, F.length(F.bin(F.expr("(n - 1) div 1024")))).otherwise(0)
    return years.withColumn("p", F.call_function("shiftleft", F.lit(16), F.greatest(F.lit(2), bits)))


def machines(spark, folder) -> list[tuple[int, int, int]]:
    return [tuple(r) for r in yearly(spark, folder).collect()]  # a row for each year


@query(f"with {MACHINES_SQL} select y, k, p, level, r from plans where k > 1")
def q33_level_plans(spark, folder):
    """Plans of machines that hold a year's orders."""
    rows = [(y, k, p, i, r) for y, _, p in machines(spark, folder) for k in (2, 3) for i, r in enumerate(plan_levels(p, k, "node"))]
    return spark.createDataFrame(rows, "y int, k int, p int, level int, r int")


# ---- operators over layouts

@query("select quantile_disc(l_extendedprice, 0.5) as median from lineitem")
def q41_exact_median(spark, folder):
    df = read_table(spark, folder, "lineitem", LINE)
    n = df.count()
    return _at_ranks(df, PRICE, [(n + 1) // 2 - 1]).select(F.col("l_extendedprice").alias("median"))


@query("select i::int as pct, (select value from (select value, row_number() over (order by value, event_id) as rn, count(*) over () as n from events) where rn = (i * n + 99) // 100) as value from (select unnest(generate_series(1, 99)) as i)")
def q42_exact_quantiles(spark, folder):
    df = read_table(spark, folder, "events", ["event_id", "value"])
    n = df.count()
    at = {i: max(0, (i * n + 99) // 100 - 1) for i in range(1, 100)}
    found = _at_ranks(df, key("value", ties=("event_id",)), sorted(set(at.values())))
    return spark.createDataFrame(list(at.items()), "pct int, at long").join(found, "at").select("pct", "value")


@query("select l_extendedprice from lineitem order by " + _PO + " limit 1 offset 1000")
def q43_kth(spark, folder):
    return splitter_sort(read_table(spark, folder, "lineitem", LINE), PRICE, P, 1, by="l_orderkey").kth(1000).select("l_extendedprice")


@query("select i::int as part, ((i + 1) * n // 16 - i * n // 16)::bigint as cnt, (select l_extendedprice from (select l_extendedprice, row_number() over (order by " + _PO + """) as rn from lineitem) where rn = i * n // 16 + 1) as low
from (select unnest(generate_series(0, 15)) as i), (select count(*) as n from lineitem)""")
def q44_equi_depth(spark, folder):
    df = read_table(spark, folder, "lineitem", LINE)
    n = df.count()
    cuts = [(i, i * n // 16, (i + 1) * n // 16 - i * n // 16) for i in range(16)]
    found = _at_ranks(df, PRICE, [c for _, c, _ in cuts])
    return spark.createDataFrame(cuts, "part int, at long, cnt long").join(found, "at").select("part", "cnt", F.col("l_extendedprice").alias("low"))


_DATE = key("l_shipdate", ties=(*LINE_TIES, "l_extendedprice"))
_DATED = [*LINE, "l_shipdate"]
_DO = "l_shipdate"


def _dated(spark, folder) -> SortedLayout:
    return splitter_sort(read_table(spark, folder, "lineitem", _DATED), _DATE, P, 1, by="l_orderkey")


def _window_query(name: str, column: str, sql: str) -> None:
    def run(spark, folder):
        c = F.round(column, 9).alias(column) if column in ("percent_rank", "cume_dist") else F.col(column).cast("long").alias(column)
        return _dated(spark, folder).rank_window().select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", c)
    QUERIES[name], ORACLES[name] = run, f"select l_orderkey, l_linenumber, l_partkey, l_suppkey, {sql} as {column} from lineitem"


_window_query("q46_g_rank", "rank", "rank() over (order by l_shipdate)::bigint")
_window_query("q47_g_dense_rank", "dense_rank", "dense_rank() over (order by l_shipdate)::bigint")
_window_query("q48_g_percent_rank", "percent_rank", "round(percent_rank() over (order by l_shipdate), 9)")
_window_query("q49_g_cume_dist", "cume_dist", "round(cume_dist() over (order by l_shipdate), 9)")


@query(f"select l_orderkey, l_linenumber, l_partkey, l_suppkey, row_number() over (order by l_shipdate, {_PO.split(', ', 1)[1]}, l_extendedprice)::bigint as row_number from lineitem")
def q45_g_row_number(spark, folder):
    return _dated(spark, folder).with_rank("row_number", 1).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "row_number")


@query("select event_id, ntile(7) over (order by ts, event_id)::int as ntile from events")
def q50_g_ntile(spark, folder):
    return _events(spark, folder).ntile(7).select("event_id", "ntile")


def _events(spark, folder) -> SortedLayout:
    return splitter_sort(read_table(spark, folder, "events"), TS, P, 1, by="event_id")


@query("select event_id, (sum(round(value * 100)::bigint) over (order by ts, event_id rows between unbounded preceding and current row))::bigint as running from events")
def q51_g_running_sum(spark, folder):
    return _events(spark, folder).running(F.round(F.col("value") * 100).cast("long")).select("event_id", "running")


@query("select event_id, lag(event_id, 2) over (order by ts, event_id) as lag, lead(event_id, 2) over (order by ts, event_id) as lead from events")
def q52_g_lag_lead(spark, folder):
    return _events(spark, folder).lag_lead("event_id", 2).select("event_id", "lag", "lead")


@query("""select event_id, first_value(event_id) over w as first, last_value(event_id) over w as last, nth_value(event_id, 2) over w as second, max(value) over w as top from events
window w as (order by ts, event_id rows between 4 preceding and current row)""")
def q53_g_first_last(spark, folder):
    w = SortedLayout.window().rowsBetween(-4, 0)
    return _events(spark, folder).frame({"first": F.first("event_id").over(w), "last": F.last("event_id").over(w), "second": F.nth_value("event_id", 2).over(w), "top": F.max("value").over(w)}, 4, 0).select("event_id", "first", "last", "second", "top")


_LK = key("l_orderkey", ties=("l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice"))


def _join_query(name: str, how: str, sql: str) -> None:
    def run(spark, folder):
        layout = splitter_sort(read_table(spark, folder, "lineitem", LINE), _LK, P, 1)
        # every order, under a key that leaves out each fifth number and goes beyond the last: rows without a partner on both sides
        other = read_table(spark, folder, "orders", ["o_orderkey", "o_totalprice"]).withColumn("o_orderkey", F.expr("o_orderkey * 5 div 4"))
        out = layout.join(other, "o_orderkey", how)
        price, total = F.sum(F.round(F.col("l_extendedprice") * 100).cast("long")).alias("cents"), F.sum(F.round(F.col("o_totalprice") * 100).cast("long")).alias("total")
        if how in ("semi", "anti"):
            return out.groupBy("l_orderkey", "l_linenumber").agg(F.count("*").alias("n"), price)
        return out.groupBy("l_orderkey", "o_orderkey", "l_linenumber").agg(F.count("*").alias("n"), price, total)
    QUERIES[name] = run
    by = "l_orderkey, l_linenumber" if how in ("semi", "anti") else "l_orderkey, o_orderkey, l_linenumber"
    total = "" if how in ("semi", "anti") else ", sum(round(o_totalprice * 100)::bigint)::bigint as total"
    ORACLES[name] = f"""select {by}, count(*)::bigint as n, sum(round(l_extendedprice * 100)::bigint)::bigint as cents{total} from lineitem {sql}
(select o_orderkey * 5 // 4 as o_orderkey, o_totalprice from orders) o on l_orderkey = o_orderkey group by {by}"""


for _how, _sql in {"inner": "join", "left": "left join", "semi": "semi join", "anti": "anti join", "full": "full join", "right": "right join"}.items():
    _join_query({"inner": "q54", "left": "q55", "semi": "q56", "anti": "q57", "full": "q58", "right": "q58b"}[_how] + f"_join_{_how}", _how, _sql)


@query("select p_partkey, count(*)::bigint as n from part join lineitem on l_extendedprice between p_retailprice * 10 and p_retailprice * 10 + 5 group by p_partkey")
def q59_theta_join(spark, folder):
    layout = splitter_sort(read_table(spark, folder, "lineitem", LINE), PRICE, P, 1, by="l_orderkey")
    part = read_table(spark, folder, "part", ["p_partkey", "p_retailprice"])
    near = layout.band_count(part, F.col("p_retailprice") * 10, F.col("p_retailprice") * 10 + 5)
    return near.groupBy("p_partkey").agg(F.sum("n").alias("n")).where("n > 0")


@query("select a.o_orderkey as k, count(*)::bigint as n from orders a join orders b on b.o_totalprice between a.o_totalprice - 20 and a.o_totalprice + 20 group by a.o_orderkey")
def q60_join_band(spark, folder):
    layout = splitter_sort(read_table(spark, folder, "orders", _OC), TOTAL, P, 1, by="o_orderkey")
    other = read_table(spark, folder, "orders", _OC).toDF("k", "t")
    return layout.band_count(other, F.col("t") - 20, F.col("t") + 20).groupBy("k").agg(F.sum("n").alias("n")).where("n > 0")


@query("""select e.event_id, p.event_id as asof_pid from events e asof left join (select * from events where event_type = 'purchase') p on e.user_id = p.user_id and e.ts >= p.ts""")
def q61_join_asof(spark, folder):
    other = read_table(spark, folder, "events", where="event_type = 'purchase'").select("user_id", F.col("ts").alias("pts"), F.col("event_id").alias("pid"))
    return _events(spark, folder).asof(other, "pts", ["user_id"], "pid").select("event_id", "asof_pid")


@query("""with a as (select o_orderkey as id, o_orderkey * 3301 as s, o_orderkey * 3301 + o_custkey % 401 as e from orders),
b as (select row_number() over (order by o_totalprice, o_orderkey) as id, round(o_totalprice * 100)::bigint as s, round(o_totalprice * 100)::bigint + o_custkey % 503 as e from orders)
select a.id as left_id, count(*)::bigint as n, sum(b.s)::bigint as starts from a join b on a.s < b.e and b.s < a.e where a.e > a.s and b.e > b.s group by a.id""")
def q62_interval_overlap(spark, folder):
    """Intervals of order numbers against intervals of prices, all orders on both sides."""
    o = read_table(spark, folder, "orders", ["o_orderkey", "o_custkey", "o_totalprice"])
    price = F.round(F.col("o_totalprice") * 100).cast("long")
    left = o.select(F.col("o_orderkey").alias("left_id"), (F.col("o_orderkey") * 3301).alias("ls"), (F.col("o_orderkey") * 3301 + F.col("o_custkey") % 401).alias("le"))
    right = o.select(price.alias("rs"), (price + F.col("o_custkey") % 503).alias("re"))
    return interval_join(left, right, "ls", "le", "rs", "re", 64).groupBy("left_id").agg(F.count("*").alias("n"), F.sum("rs").alias("starts"))


@query("""with o as (select o_orderkey as id, round(o_totalprice * 100)::bigint as s, round(o_totalprice * 100)::bigint + o_custkey % 97 as e from orders)
select a.id as left_id, b.id as right_id from o a, o b where a.s < b.e and b.s < a.e and a.e > a.s and b.e > b.s""")
def q62b_interval_overlap_whole(spark, folder):
    o = read_table(spark, folder, "orders", ["o_orderkey", "o_custkey", "o_totalprice"])
    start = F.round(F.col("o_totalprice") * 100).cast("long")
    make = lambda x: o.select(F.col("o_orderkey").alias(f"{x}_id"), start.alias(f"{x}s"), (start + F.col("o_custkey") % 97).alias(f"{x}e"))
    return interval_join(make("left"), make("right"), "lefts", "lefte", "rights", "righte", 64).select("left_id", "right_id")


@query("select doc_id, n_chars from (select *, row_number() over (partition by text order by doc_id) as rn from documents) where rn = 1")
def q63_dedupe_sort(spark, folder):
    return splitter_sort(read_table(spark, folder, "documents", ["doc_id", "text", "n_chars"]), key("text", ties=("doc_id",)), P, 1, by="doc_id").dedupe().select("doc_id", "n_chars")


@query("select (row_number() over (order by k, src) - 1)::bigint as rank, k, src from (select c_custkey as k, 'c' as src from customer union all select o_custkey, 'o' from (select distinct o_custkey from orders))")
def q64_union_sorted(spark, folder):
    both = read_table(spark, folder, "customer").select(F.col("c_custkey").alias("k"), F.lit("c").alias("src")).unionByName(read_table(spark, folder, "orders").select(F.col("o_custkey").alias("k")).distinct().withColumn("src", F.lit("o")))
    return _ranked(splitter_sort(both, key("k", "src"), P, 1, by="k"), "k", "src")


@query("select o_custkey as k from orders intersect all select l_orderkey % 1000 from lineitem")
def q65_intersect_all(spark, folder):
    return set_op(read_table(spark, folder, "orders").select(F.col("o_custkey").alias("k")), read_table(spark, folder, "lineitem").select((F.col("l_orderkey") % 1000).alias("k")), ["k"], "intersect")


@query("select o_custkey as k from orders except all select c_custkey from customer")
def q66_except_all(spark, folder):
    return set_op(read_table(spark, folder, "orders").select(F.col("o_custkey").alias("k")), read_table(spark, folder, "customer").select(F.col("c_custkey").alias("k")), ["k"], "except")


@query("select l_suppkey, sum(round(l_extendedprice * 100)::bigint)::bigint as cents, count(*)::bigint as n from lineitem group by l_suppkey")
def q67_sort_agg(spark, folder):
    layout = splitter_sort(read_table(spark, folder, "lineitem", LINE), key("l_suppkey", ties=("l_orderkey", "l_partkey", "l_linenumber", "l_extendedprice")), P, 1, by="l_orderkey")
    cents = F.round(F.col("l_extendedprice") * 100).cast("long")
    return layout.group_agg(["l_suppkey"], {"c": F.sum(cents), "k": F.count("*")}, {"cents": F.sum("c"), "n": F.sum("k")})


def _sets_query(name: str, kind: str) -> None:
    spark_kind = {"rollup": "rollup(f, s, y)", "cube": "cube(f, s, y)", "sets": "grouping sets ((f, s), (y), ())"}[kind]

    def run(spark, folder):
        t = read_table(spark, folder, "lineitem").select(F.col("l_returnflag").alias("f"), F.col("l_linestatus").alias("s"), F.year("l_shipdate").alias("y"))
        return spark.sql(f"select f, s, y, count(*) as n from {{t}} group by {spark_kind}", t=t)
    QUERIES[name] = run
    ORACLES[name] = f"select f, s, y::int as y, count(*)::bigint as n from (select l_returnflag as f, l_linestatus as s, year(l_shipdate) as y from lineitem) group by {spark_kind}"


_sets_query("q68_rollup", "rollup")
_sets_query("q69_cube", "cube")
_sets_query("q70_grouping_sets", "sets")


@query("select l_returnflag, count(distinct l_suppkey)::bigint as suppliers, (count(*) filter (where l_quantity > 25))::bigint as large, (count(*) filter (where l_linestatus = 'O'))::bigint as \"O\", (count(*) filter (where l_linestatus = 'F'))::bigint as \"F\" from lineitem group by l_returnflag")
def q71_distinct_agg(spark, folder):
    return read_table(spark, folder, "lineitem").groupBy("l_returnflag").agg(
        F.count_distinct("l_suppkey").alias("suppliers"), F.count_if(F.col("l_quantity") > 25).alias("large"), F.count_if(F.col("l_linestatus") == "O").alias("O"), F.count_if(F.col("l_linestatus") == "F").alias("F"))


@query("select o_orderkey, o_orderdate from orders where o_orderdate >= timestamp '1995-01-01' and o_orderdate <= timestamp '1995-03-01'")
def q72_range_scan(spark, folder):
    layout = splitter_sort(read_table(spark, folder, "orders", ["o_orderkey", "o_orderdate"]), key("o_orderdate", ties=("o_orderkey",)), P, 1, by="o_orderkey")
    return layout.range_scan(F.expr("timestamp_ntz'1995-01-01'"), F.expr("timestamp_ntz'1995-03-01'")).select("o_orderkey", "o_orderdate")


_PD = key("l_extendedprice", desc=("l_extendedprice",), ties=LINE_TIES)
_PDO = "l_extendedprice desc, l_orderkey, l_partkey, l_suppkey, l_linenumber"


@query(f"select (row_number() over (order by {_PDO}) - 1)::bigint as rank, {', '.join(LINE)} from lineitem qualify rank < 25")
def q73_top_k(spark, folder):
    return splitter_sort(read_table(spark, folder, "lineitem", LINE), _PD, P, 1, by="l_orderkey").top_k(25).select("rank", *LINE)


@query(f"select (row_number() over (order by {_PDO}) - 1)::bigint as rank, {', '.join(LINE)} from lineitem qualify rank between 5000 and 5099")
def q74_limit_offset(spark, folder):
    return splitter_sort(read_table(spark, folder, "lineitem", LINE), _PD, P, 1, by="l_orderkey").slice(5000, 100).select("rank", *LINE)


@query("select (row_number() over (order by url, page_id) - 1)::bigint as rank, page_id, upper(url) as up, split_part(url, '/', 3) as host, regexp_replace(url, '[0-9]+', '#', 'g') as shape, length(trim(url))::int as len from pages")
def q75_string_funcs(spark, folder):
    layout = splitter_sort(read_table(spark, folder, "pages", ["page_id", "url"]), key("url", ties=("page_id",)), P, 1, by="page_id")
    return layout.with_rank().select("rank", "page_id", F.upper("url").alias("up"), F.split_part("url", F.lit("/"), F.lit(3)).alias("host"), F.regexp_replace("url", "[0-9]+", "#").alias("shape"), F.length(F.trim("url")).alias("len"))


@query("select o_orderkey, date_trunc('month', o_orderdate)::timestamp as month, year(o_orderdate)::int as y, dayofweek(o_orderdate)::int + 1 as dow, datediff('day', date '1992-01-01', o_orderdate::date)::int as days from orders")
def q76_date_funcs(spark, folder):
    return read_table(spark, folder, "orders").select("o_orderkey", F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("month"), F.year("o_orderdate").alias("y"), F.dayofweek("o_orderdate").alias("dow"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days"))


@query("select (row_number() over (order by k nulls first, event_id) - 1)::bigint as rank, event_id, k from (select event_id, (json_extract_string(props, '$.k'))::bigint as k from events)")
def q77_json_funcs(spark, folder):
    df = read_table(spark, folder, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))
    return _ranked(splitter_sort(df, key("k", ties=("event_id",)), P, 1, by="event_id"), "event_id", "k")


@query("select vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::double * x::double))), 6) as norm, len(list_filter(embedding, lambda x: x > 0))::int as positive from embeddings")
def q78_array_funcs(spark, folder):
    return read_table(spark, folder, "embeddings").select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))), 6).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"))


_CELL = "greatest(0, least(15, floor((embedding[{}]::double + 4) / 8 * 16)))::int"
_MORTON = " | ".join(f"((({'xyz'[i]} >> {b}) & 1) << {b * 3 + 2 - i})" for b in range(4) for i in range(3))


@query(f"select (row_number() over (order by m, vec_id) - 1)::bigint as rank, vec_id, m from (select vec_id, ({_MORTON})::bigint as m from (select vec_id, {_CELL.format(1)} as x, {_CELL.format(2)} as y, {_CELL.format(3)} as z from embeddings))")
def q79_morton(spark, folder):
    cells = [quantised(F.col("embedding")[i].cast("double"), -4.0, 4.0, 4) for i in range(3)]
    df = read_table(spark, folder, "embeddings").select("vec_id", morton_key(cells, 4).alias("m"))
    return _ranked(splitter_sort(df, key("m", ties=("vec_id",)), P, 2, by="vec_id"), "vec_id", "m")


# ---- windows in time, runs

@query("select time_bucket(interval '1 hour', ts) as start, event_type, count(*)::bigint as n from events group by 1, 2")
def q80_tumbling(spark, folder):
    return read_table(spark, folder, "events").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("select s as start, count(*)::bigint as n from (select unnest([time_bucket(interval '1 hour', ts), time_bucket(interval '1 hour', ts) - interval '1 hour']) as s from events) group by s")
def q81_sliding(spark, folder):
    return read_table(spark, folder, "events").groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@query("""select user_id, min(ts) as first, max(ts) as last, count(*)::bigint as n from (select *, sum(fresh) over (partition by user_id order by ts, event_id) as s from
(select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval '6 hours' then 0 else 1 end as fresh from events)) group by user_id, s""")
def q82_session(spark, folder):
    w = F.session_window("ts", "6 hours")
    return read_table(spark, folder, "events").groupBy("user_id", w.alias("w")).agg(F.min("ts").alias("first"), F.max("ts").alias("last"), F.count("*").alias("n")).drop("w")


@query("""select event_id, ts < top - interval '2 hours' as late from (select event_id, ts, max(ts) over (order by a, event_id rows between unbounded preceding and current row) as top from
(select event_id, ts, event_id + case when event_id % 20 = 0 then 500 else 0 end as a from events))""")
def q83_late_split(spark, folder):
    df = read_table(spark, folder, "events", ["event_id", "ts"]).withColumn("a", F.col("event_id") + F.when(F.col("event_id") % 20 == 0, 500).otherwise(0))
    out = splitter_sort(df, key("a", "event_id"), P, 1, by="event_id").running(F.col("ts"), "max", "top")
    return out.select("event_id", (F.col("ts") < F.col("top") - F.expr("interval 2 hours")).alias("late"))


@query("select (row_number() over (order by ts, event_id) - 1)::bigint as rank, (event_id % 8)::int as run, event_id from events")
def q84_run_merge(spark, folder):
    from tiersort.streaming.runs import merge_runs

    return merge_runs(read_table(spark, folder, "events").withColumn("run", (F.col("event_id") % 8).cast("int")), TS, P).with_rank().select("rank", "run", "event_id")


# ---- tables together

@query("select doc_id, lang, n_chars, quality, toxic from (select d.*, quality, toxic, row_number() over (partition by lang order by n_chars desc, d.doc_id) as rn from documents d join labels l on d.doc_id = l.doc_id) where rn <= 10")
def q85_label_join(spark, folder):
    docs = read_table(spark, folder, "documents", ["doc_id", "lang", "n_chars"]).join(read_table(spark, folder, "labels"), "doc_id")
    w = Window.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id")
    return docs.withColumn("rn", F.row_number().over(w)).where("rn <= 10").select("doc_id", "lang", "n_chars", "quality", "toxic")


@query("select conv_id, turn, role, (turn - lag(turn) over (partition by conv_id order by turn)) <> 1 as gap from conversations")
def q86_turns(spark, folder):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return read_table(spark, folder, "conversations").select("conv_id", "turn", "role", (F.col("turn") - F.lag("turn").over(w) != 1).alias("gap"))


@query("select item_id, (row_number() over (order by length(text), item_id) - 1)::bigint as rank from benchmark")
def q87_bench_rank(spark, folder):
    df = read_table(spark, folder, "benchmark").select("item_id", F.length("text").alias("n"))
    return _ranked(splitter_sort(df, key("n", ties=("item_id",)), P, 1, by="item_id"), "item_id")


@query("""select r_name, n_name, cents, rank() over (partition by r_name order by cents desc, n_name)::int as place from (select r_name, n_name, sum(round(l_extendedprice * 100)::bigint)::bigint as cents
from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by all)""")
def q88_star_sorted(spark, folder):
    t = (read_table(spark, folder, "lineitem", ["l_suppkey", "l_extendedprice"]).join(read_table(spark, folder, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
         .join(read_table(spark, folder, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(read_table(spark, folder, "region"), F.col("n_regionkey") == F.col("r_regionkey")))
    t = t.groupBy("r_name", "n_name").agg(F.sum(F.round(F.col("l_extendedprice") * 100).cast("long")).alias("cents"))
    return t.withColumn("place", F.rank().over(Window.partitionBy("r_name").orderBy(F.desc("cents"), "n_name")))


@query()
def q89_imbalance_grid(spark, folder):
    """Imbalance of packed groups by oversampling and overpartitioning."""
    from tiersort.plans.workloads import ab_grid

    return ab_grid(read_table(spark, folder, "orders", _OC), TOTAL, "o_orderkey", 16, [4, 8], [1, 4, 16])


@query("""select pe, count(*)::bigint as cnt, min(o_totalprice) as first, max(o_totalprice) as last from
(select o_totalprice, ((row_number() over (order by o_totalprice, o_orderkey) * 8 - 1) // (select count(*) from orders))::int as pe from orders) group by pe""")
def q90_write_read_layout(spark, folder):
    from tiersort.sources.sinks import read_sorted, scratch, write_sorted

    path = scratch(spark)
    write_sorted(merge_sort(read_table(spark, folder, "orders", _OC), TOTAL, P, 1, by="o_orderkey"), path)
    return read_sorted(spark, path, TOTAL, P).df.groupBy(F.col("_ms_pe").alias("pe")).agg(F.count("*").alias("cnt"), F.min("o_totalprice").alias("first"), F.max("o_totalprice").alias("last"))


@query(f"with {MACHINES_SQL} select y, p, level, r from plans where k = 3")
def q91_level_plan_udtf(spark, folder):
    from tiersort.functions.udfs import register

    register(spark)
    return spark.sql("select y, p, level, r from {t}, lateral level_plan(p, 3, 'node')", t=yearly(spark, folder))


@query("select grp, sum(to_pos - from_pos)::bigint as words, (sum(case when pe // 4 <> target // 4 then to_pos - from_pos else 0 end))::bigint as crossing from (" + _cut_sql("pe") + ") group by grp")
def q92_cross_volume(spark, folder):
    return d.cross_volume(d.deliver(_orders_pieces(spark, folder), "prefix"), 4)
