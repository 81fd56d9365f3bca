"""More of the catalogue: variants, measures and experiments of the sorts, and operators around them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tiersort.functions import costmodel as cost
from tiersort.functions.keys import key
from tiersort.functions.mixing import FACTOR, PRIME, morton_key, quantised
from tiersort.operators import baselines as base
from tiersort.operators import delivery as d
from tiersort.operators.layout import equi_width, merge_layouts
from tiersort.operators.packing import packing_table
from tiersort.operators.sort import merge_sort, place, splitter_sort
from tiersort.operators.splitters import bucket_sizes, classify, grid_rank, grid_sort
from tiersort.plans import workloads
from tiersort.plans.catalog import MACHINES_SQL, _CELL, _MORTON, _OC, _PACK, _PIECES, _PO, _SAMPLE, LINE, ORACLES, P, PRICE, QUERIES, TOTAL, TS, _cut_sql, _mms, _mss, _orders_pieces, _ranked, _sort_query, _splitters, machines, query
from tiersort.plans.topology import plan_levels
from tiersort.sources.sinks import read_sorted, scratch, staged, write_sorted
from tiersort.sources.tables import read_table

_OO = "o_totalprice, o_orderkey"


# ---- variants of the sorts

def _orders_sort(name: str, how, with_pe: bool = False) -> None:
    _sort_query(name, "orders", _OC, TOTAL, _OO, how, with_pe)


_orders_sort("q101_mss_grid_sample", _mss(TOTAL, 2, sample_sort="grid"))
_orders_sort("q102_mss_prefix", _mss(TOTAL, 2, delivery="prefix"))
_orders_sort("q102b_mss_permuted", _mss(TOTAL, 2, delivery="permuted"))
_orders_sort("q102c_mss_chunked", _mss(TOTAL, 2, delivery="chunked", capacity="bound"))
_orders_sort("q103_mss_reuse", _mss(TOTAL, 2, ties="origin", reuse=True))
_orders_sort("q104_mss_staged", _mss(TOTAL, 2, form="staged"))
_orders_sort("q104b_mss_wide_packing", _mss(TOTAL, 1, packing="wide"))
_orders_sort("q104c_mss_bisect_packing", _mss(TOTAL, 1, packing="bisect"))
_orders_sort("q105_mms_permuted", _mms(TOTAL, 2, delivery="permuted"), True)
_orders_sort("q105b_mms_chunked", _mms(TOTAL, 2, delivery="chunked"), True)
_orders_sort("q105c_mms_prefix", _mms(TOTAL, 2, delivery="prefix"), True)
_orders_sort("q105d_mms_multipass", _mms(TOTAL, 1, fan_in=2), True)
_orders_sort("q105e_mms_timsort", _mms(TOTAL, 2, merge="timsort"), True)
_sort_query("q40b_spark_sort_price", "lineitem", LINE, PRICE, _PO, lambda df: base.spark_sort(df, PRICE, P))


def _ties_query(mode: str) -> None:
    def run(spark, folder):
        return _ranked(splitter_sort(read_table(spark, folder, "lineitem", ["l_discount"]), key("l_discount"), P, 2, ties=mode), "l_discount")
    QUERIES[f"q106_ties_{mode}"] = run
    ORACLES[f"q106_ties_{mode}"] = "select (row_number() over (order by l_discount) - 1)::bigint as rank, l_discount from lineitem"


for _mode in ("origin", "level", "none"):
    _ties_query(_mode)


@query("select true as balanced, count(*)::bigint as n from orders")
def q107_mss_eps(spark, folder):
    """The wanted imbalance is kept."""
    layout = splitter_sort(read_table(spark, folder, "orders", _OC), TOTAL, P, 2, eps=0.25)
    return layout.load_stats().select((F.col("eps") <= 0.25).alias("balanced"), F.round(F.col("mean_load") * P).cast("long").alias("n"))


@query(f"select (row_number() over (order by m, vec_id) - 1)::bigint as rank, vec_id, m from (select vec_id, ({_MORTON})::bigint as m from (select vec_id, {_CELL.format(1)} as x, {_CELL.format(2)} as y, {_CELL.format(3)} as z from embeddings))")
def q79b_morton_small_n(spark, folder):
    """Few rows on many PEs: halving on each of log2 p levels."""
    cells = [quantised(F.col("embedding")[i].cast("double"), -4.0, 4.0, 4) for i in range(3)]
    df = read_table(spark, folder, "embeddings").select("vec_id", morton_key(cells, 4).alias("m"))
    return _ranked(splitter_sort(df, key("m", ties=("vec_id",)), 64, "log"), "vec_id", "m")


@query("select (row_number() over (order by o_orderpriority desc, o_totalprice::decimal(12, 2) desc, o_orderkey) - 1)::bigint as rank, o_orderkey from orders")
def q16b_sort_struct(spark, folder):
    df = read_table(spark, folder, "orders").select("o_orderkey", F.struct("o_orderpriority", F.col("o_totalprice").cast("decimal(12,2)")).alias("s"))
    return _ranked(splitter_sort(df, key("s", desc=("s",), ties=("o_orderkey",)), P, 2), "o_orderkey")


@query("select (row_number() over (order by o_totalprice::decimal(24, 4), o_orderkey) - 1)::bigint as rank, o_orderkey from orders")
def q16c_sort_decimal(spark, folder):
    df = read_table(spark, folder, "orders").select("o_orderkey", F.col("o_totalprice").cast("decimal(24,4)").alias("d"))
    return _ranked(merge_sort(df, key("d", ties=("o_orderkey",)), P, 1), "o_orderkey")


@query("select (row_number() over (order by embedding, vec_id) - 1)::bigint as rank, vec_id from embeddings")
def q14c_sort_array(spark, folder):
    return _ranked(splitter_sort(read_table(spark, folder, "embeddings", ["vec_id", "embedding"]), key("embedding", ties=("vec_id",)), P, 2), "vec_id")


@query("select placement, (row_number() over (partition by placement order by ts, event_id) - 1)::bigint as rank, event_id from events, (values ('input'), ('hash'), ('cyclic'), ('block'), ('skew')) v(placement)")
def q108_adversarial(spark, folder):
    """Sorted input, and inputs dealt out otherwise, up to nine of ten rows on one PE."""
    out, df = None, read_table(spark, folder, "events", ["event_id", "ts"])
    for how in ("input", "hash", "cyclic", "block", "skew"):
        one = _ranked(splitter_sort(df, TS, P, 2, by="event_id", placement=how), "event_id").withColumn("placement", F.lit(how))
        out = one if out is None else out.unionByName(one)
    return out


@query("select (row_number() over (order by substr(text, 1, 10), doc_id) - 1)::bigint as rank, doc_id from documents")
def q109_disk_to_disk(spark, folder):
    """Records with keys of ten characters, read from files and written to files in order."""
    df = read_table(spark, folder, "documents", ["doc_id", "text"]).withColumn("k", F.substring("text", 1, 10))
    by, path = key("k", ties=("doc_id",)), scratch(spark, "records")
    write_sorted(splitter_sort(df, by, P, 2), path)
    return _ranked(read_sorted(spark, path, by, P), "doc_id")


# ---- building blocks

_H = f"((o_orderkey % {PRIME} + 1) * {FACTOR}) % {PRIME}"


@query(f"""select how, pe::int as pe, count(*)::bigint as cnt from (select 'hash' as how, {_H} % 8 as pe from orders union all select 'cyclic', o_orderkey % 8 from orders
union all select 'block', least(7, floor(o_orderkey * 8 / (select max(o_orderkey) + 1 from orders)::double)) from orders
union all select 'skew', case when {_H} % 10 < 9 then 0 else o_orderkey % 8 end from orders) group by how, pe""")
def q110_placements(spark, folder):
    out, df = None, read_table(spark, folder, "orders", _OC)
    for how in ("hash", "cyclic", "block", "skew"):
        one = place(df, 8, how, "o_orderkey").groupBy(F.col("_ms_pe").alias("pe")).agg(F.count("*").alias("cnt")).withColumn("how", F.lit(how))
        out = one if out is None else out.unionByName(one)
    return out


def _held_sql(p: int) -> str:
    return f"h as (select pe::int as pe, count(o_orderkey) as w from range({p}) r(pe) left join orders on o_orderkey % {p} = pe group by pe)"


def _held(spark, folder, p: int) -> DataFrame:
    """Orders of each of p PEs."""
    return read_table(spark, folder, "orders", ["o_orderkey"]).groupBy((F.col("o_orderkey") % p).cast("int").alias("pe")).agg(F.count("*").alias("words"))


@query(f"with {_held_sql(16)} select j::int as round, s::int as src, xor(s, 1 << j)::int as dst, sum(w)::bigint as words from range(4) a(j), range(16) b(s), h where pe >> j = s >> j group by j, s")
def q111_gossip_hypercube(spark, folder):
    """All PEs come to hold all orders."""
    return d.gossip_schedule(spark, 16, held=_held(spark, folder, 16))


@query(f"""with {_held_sql(11)}, u as (select j, s, 1 << j as w from range(4) a(j), range(11) b(s) where s % (2 << j) = (1 << j))
select j::int as round, s::int as src, (s - u.w)::int as dst, sum(h.w)::bigint as words from u, h where pe >> j = s >> j group by j, s, u.w
union all select (7 - j)::int, (s - w)::int, s::int, (select sum(w) from h)::bigint from u""")
def q111b_gossip_tree(spark, folder):
    return d.gossip_schedule(spark, 11, how="tree", held=_held(spark, folder, 11))


@query("select (rn - 1)::bigint as rank, p_partkey, ((rn * 8 - 1) // n)::int as pe from (select p_partkey, row_number() over (order by p_retailprice, p_partkey) as rn, count(*) over () as n from part)")
def q112_grid_sort(spark, folder):
    layout = grid_sort(read_table(spark, folder, "part", ["p_partkey", "p_retailprice"]), key("p_retailprice", ties=("p_partkey",)), 8)
    return layout.with_rank().select("rank", "p_partkey", F.col("_ms_pe").alias("pe"))


@query("select s_suppkey, rank from (select s_suppkey, (row_number() over (order by s_acctbal, s_suppkey) - 1)::bigint as rank from supplier) where rank in (0, 3, 7)")
def q112b_grid_wanted(spark, folder):
    return grid_rank(read_table(spark, folder, "supplier"), key("s_acctbal", ties=("s_suppkey",)), 6, wanted=[0, 3, 7]).select("s_suppkey", "rank")


@query(f"with {_PIECES} select grp, pe, size, (base + (pe // 4) % q)::int as at from pg")
def q113_descriptors(spark, folder):
    return d.route_descriptors(_orders_pieces(spark, folder), 4)


def _slices_sql(pieces: str, method: str) -> str:
    """Slices of a piece table ``pg`` (pe, grp, base, q, size, m), as CTEs that end in ``sl``."""
    if method == "two_phase":
        return f"""{pieces}, f as (select *, sum(size) over () as n, (select max(ceil(m / q))::bigint from pg) as cap, (select count(distinct grp) from pg) as r from pg),
sm as (select *, least(q - 1, (count(*) over (partition by grp order by pe rows between unbounded preceding and 1 preceding) * q) // 64) as t from f where size * 2 * 64 * r <= n),
rm as (select g.grp, g.t, g.cap - coalesce(w.given, 0) as free from (select distinct grp, cap, unnest(generate_series(0, q - 1)) as t from f) g left join (select grp, t, sum(size) as given from sm group by all) w on g.grp = w.grp and g.t = w.t),
rx as (select *, coalesce(sum(free) over (partition by grp order by t rows between unbounded preceding and 1 preceding), 0) as x from rm),
ly as (select *, coalesce(sum(size) over (partition by grp order by pe rows between unbounded preceding and 1 preceding), 0) as y from f where size * 2 * 64 * r > n),
sl as (select grp, pe, 0 as a, size as b, base + t as target from sm union all select ly.grp, pe, greatest(x, y) - y, least(x + free, y + size) - y, base + t from ly join rx on ly.grp = rx.grp and x < y + size and y < x + free)"""
    if method == "chunked":
        return f"""{pieces}, ch as (select *, greatest(1, (ceil(m / q)::bigint) // (2 * q)) as chunk from pg),
cc as (select *, unnest(generate_series(0, (size - 1) // chunk)) as c from ch),
cd as (select grp, pe, base, q, m, c, c * chunk as lead, least(chunk, size - c * chunk) as size from cc),
st as (select *, coalesce(sum(size) over (partition by grp order by ((pe::bigint * 4096 + c) * 7919 + grp * 104729 + 1) * 48271 % 2147483647, pe, c rows between unbounded preceding and 1 preceding), 0)::bigint as start from cd),
x as (select *, unnest(generate_series(start * q // m, (start + size - 1) * q // m)) as t from st),
sl as (select grp, pe, greatest((t * m + q - 1) // q, start) - start + lead as a, least(((t + 1) * m + q - 1) // q, start + size) - start + lead as b, base + t as target from x)"""
    order = "pe" if method == "prefix" else "(pe::bigint * 7919 + grp * 104729 + 1) * 48271 % 2147483647, pe"
    return f"""{pieces}, st as (select *, coalesce(sum(size) over (partition by grp order by {order} rows between unbounded preceding and 1 preceding), 0)::bigint as start from pg),
x as (select *, unnest(generate_series(start * q // m, (start + size - 1) * q // m)) as t from st),
sl as (select grp, pe, greatest((t * m + q - 1) // q, start) - start as a, least(((t + 1) * m + q - 1) // q, start + size) - start as b, base + t as target from x)"""


_TINY = """pg as (select pe::int as pe, g * 16 as grp, g * 16 as base, 16 as q, size::bigint as size, (sum(size) over (partition by g))::bigint as m from (
select p.range as pe, g.range as g, case when g.range = 0 and p.range < 60 then 1 else 1000 end as size from range(64) p, range(4) g))"""


def _worst_sql(pieces: str) -> str:
    parts = []
    for method in ("prefix", "permuted", "chunked", "two_phase"):
        parts.append(f"""select * from (with {_slices_sql(pieces, method)}, one as (select * from sl where b > a),
s as (select pe, count(distinct target) as n, sum(b - a) as w from one group by pe), g as (select target, count(distinct pe) as n, sum(b - a) as w from one group by target)
select '{method}' as method, (select max(n) from s)::bigint as max_sent, (select avg(n) from s) as mean_sent, (select max(w) from s)::bigint as words_sent, (select sum(n) from s)::bigint as messages,
(select max(n) from g)::bigint as max_recv, (select avg(n) from g) as mean_recv, (select max(w) from g)::bigint as words_recv, greatest((select max(w) from s), (select max(w) from g))::bigint as bottleneck)""")
    return " union all ".join(parts)


_FEW = f"""pg as (select pe::int as pe, g * 16 as grp, g * 16 as base, 16 as q, size::bigint as size, (sum(size) over (partition by g))::bigint as m from (
select p.range as pe, g.range as g, case when ((p.range * 4 + g.range + 1) * {FACTOR}) % {PRIME} % 4 = 0 then 1000 else 1 end as size from range(64) p, range(4) g))"""


@query(_worst_sql(_TINY))
def q30_messages_worst(spark, folder):
    """A run of PEs with one element each for a group."""
    return workloads.delivery_worst(spark, "tiny_run", 64, 4)


@query(_worst_sql(_FEW))
def q30b_messages_few_large(spark, folder):
    """All but a few pieces of each group hold one element."""
    return workloads.delivery_worst(spark, "few_large", 64, 4)


@query(f"select exchange, case when exchange = 'dense' then 16 * 15 else n end::bigint as messages from (select count(distinct pe * 100 + target) as n from ({_cut_sql('pe')})), (values ('dense'), ('one_factor')) v(exchange)")
def q114_exchanges(spark, folder):
    """Messages of a dense exchange and of one that leaves empty ones out."""
    slices = staged(d.deliver(_orders_pieces(spark, folder), "prefix"), "slices")
    return d.message_stats(slices, "dense", 16).select("messages", F.lit("dense").alias("exchange")).unionByName(
        d.message_stats(slices).select("messages", F.lit("one_factor").alias("exchange")))


@query(f"""with recursive {_PACK}, ld as (select part, sum(size) as load from walk join best on walk.l = best.l join z on z.bucket = walk.bucket group by part)
select max(load)::bigint as max_load, sum(load) / 4.0 as mean_load, round(max(load) * 4.0 / sum(load) - 1, 9) as eps from ld""")
def q31_mss_loads(spark, folder):
    """Balance after one level whose sample SQL can draw."""
    df, splitters = _splitters(spark, folder)
    sizes = staged(bucket_sizes(classify(df, splitters, TOTAL)), "sizes")
    parts = packing_table(sizes, 4).join(sizes, ["grp", "bucket"]).groupBy("part").agg(F.sum("size").alias("load"))
    return parts.agg(F.max("load").alias("max_load"), (F.sum("load") / 4).alias("mean_load"), F.round(F.max("load") * 4 / F.sum("load") - 1, 9).alias("eps"))


@query()
def q31b_mss_final_loads(spark, folder):
    return splitter_sort(read_table(spark, folder, "orders", _OC), TOTAL, P, 2).load_stats()


@query(f"with {_SAMPLE}, z as (select bucket, count(*) as size from b group by bucket) select round(max(size) * 4.0 / sum(size), 9) as largest, round(sum(case when size < 0.25 * (select count(*) from orders) / 4 then size else 0 end) / sum(size), 9) as in_small from z")
def q115_bucket_spread(spark, folder):
    """The largest bucket in shares of a part, and how many rows lie in buckets below a quarter of a part."""
    df, splitters = _splitters(spark, folder)
    sizes = bucket_sizes(classify(df, splitters, TOTAL)).withColumn("n", F.sum("size").over(Window.partitionBy("grp")))
    small = F.sum(F.when(F.col("size") < 0.25 * F.col("n") / 4, F.col("size")).otherwise(0))
    return sizes.agg(F.round(F.max("size") * 4.0 / F.sum("size"), 9).alias("largest"), F.round(small / F.sum("size"), 9).alias("in_small"))


# ---- measures

@query("select 2 as hops, count(*)::bigint as n from orders")
def q116_hops(spark, folder):
    """How often every row has moved in a sort of two levels."""
    layout = splitter_sort(read_table(spark, folder, "orders", _OC), TOTAL, P, 2, hops=True)
    return layout.df.groupBy(F.col("_ms_hops").alias("hops")).agg(F.count("*").alias("n"))


@query("select k::int as k, level::int as level, ranks::int as ranks from (values (1, 0, 7), (2, 0, 3), (2, 1, 4)) t(k, level, ranks)")
def q117_ranks_per_level(spark, folder):
    """Simultaneous selections: p - 1 with one level, about r for each group with more."""
    out, df = [], read_table(spark, folder, "orders", _OC)
    for k in (1, 2):
        report = merge_sort(df, TOTAL, P, k).report
        out += [(k, r["level"], r["ranks"]) for r in report.rows if r["phase"] == "splitter selection"]
        report.release()
    return spark.createDataFrame(out, "k int, level int, ranks int")


@query(f"""with {MACHINES_SQL}, sums as (select y, k, sum(100000.0 * r + n / p) as cost from plans group by y, k), best as (select y, arg_min(k, cost) as k from sums group by y)
select 'topology' as how, y, p, level::int as level, r from (select y, p, row_number() over (partition by y order by place) - 1 as level, r from (select y, p, 0 as place, 4 as r from m union all select y, p, 1, (p // 64)::int from m where p > 64 union all select y, p, 2, 16 from m))
union all select 'log', y, p, unnest(generate_series(0, bits + 3))::int, 2 from m union all select 'auto', y, p, level, r from plans join best using (y, k)""")
def q118_plans(spark, folder):
    """Plans for machines that hold a year's orders: by their shape (four islands of nodes of 16), by halves, and the cheapest."""
    plans = [(how, y, p, plan) for y, n, p in machines(spark, folder) for how, plan in (
        ("topology", plan_levels(p, 3, "topology", shape=[4, p // 64, 16])), ("log", plan_levels(p, "log")), ("auto", plan_levels(p, "auto", "node", rows=n)))]
    return spark.createDataFrame([(how, y, p, i, r) for how, y, p, plan in plans for i, r in enumerate(plan)], "how string, y int, p int, level int, r int")


@query(f"with {MACHINES_SQL} select y, p, k, (case when k = 1 then p - 1 else sum(r) end)::bigint as startups, (count(*) filter (where r > 1))::int as moves from plans group by y, p, k")
def q119_startups(spark, folder):
    """Messages of a PE and moves of an element by level count, on machines that hold a year's orders."""
    plans = [(y, p, k, plan_levels(p, k, "node")) for y, _, p in machines(spark, folder) for k in (1, 2, 3)]
    return spark.createDataFrame([(y, p, k, cost.startups(plan), cost.moves(plan)) for y, p, k, plan in plans], "y int, p int, k int, startups long, moves int")


@query(f"""with {MACHINES_SQL}, t as (select *, (n + 63) // 64 as tree from m) select what, y, pes::int as p, rounds::int as rounds from (
select 'hypercube' as what, y, p as pes, bits + 4 as rounds from t union all select 'tree', y, tree, case when tree > 1 then 2 * length(bin(tree - 1)) else 0 end from t
union all select 'merging', y, p, bits + 2 from t union all select 'selection', y, p, case when n > 1 then length(bin(n - 1)) else 0 end from t)""")
def q120_rounds(spark, folder):
    """Collective rounds on machines that hold a year's orders: gossip (the tree on as many PEs as 64 rows each fill), the merging network of delivery with r = 4, halvings of a selection."""
    rows = [(what, y, pes, cost.rounds(what, pes, *more)) for y, n, p in machines(spark, folder) for what, pes, more in (
        ("hypercube", p, ()), ("tree", -(-n // 64), ()), ("merging", p, (4,)), ("selection", p, (2, n)))]
    return spark.createDataFrame(rows, "what string, y int, p int, rounds int")


@query()
def q121_comparisons(spark, folder):
    """Comparisons of a PE and predicted seconds of both sorts and of the logarithmic one, for a year's orders."""
    rows = []
    for y, n, p in machines(spark, folder):
        for k in (1, 2, 3):
            plan = plan_levels(p, k, "node")
            rows.append((y, n, p, k, cost.comparisons(n, p, plan), cost.comparisons(n, p, plan, algorithm="merge"), cost.splitter_sort(n, p, plan, 0.2, 1e-5, 1e-9), cost.merge_sort(n, p, plan, 1e-5, 1e-9),
                         cost.logarithmic_sort(n, p, 1e-5, 1e-9)))
    return spark.createDataFrame(rows, "y int, n long, p int, k int, splitter double, merge double, splitter_seconds double, merge_seconds double, logarithmic_seconds double")


# ---- experiments

_RUN: dict[str, DataFrame] = {}


def _metrics(spark) -> DataFrame:
    """One weak-scaling run for each session: 40 sorts of few random keys."""
    name = spark.sparkContext.applicationId
    if name not in _RUN:
        _RUN[name] = workloads.weak_scaling(spark, [100], [4, 8], [1, 2], repeat=5).persist()
    return _RUN[name]


@query()
def q122_weak_scaling(spark, folder):
    return _metrics(spark)


@query()
def q122b_best_levels(spark, folder):
    return workloads.efficiencies(_metrics(spark))


def _customer_metrics(spark, folder) -> DataFrame:
    """As ``_metrics``, of a table's keys: the most PEs take all customers, fewer PEs as many for each PE."""
    keys = read_table(spark, folder, "customer", ["c_custkey", "c_acctbal"]).toDF("id", "key")
    return workloads.weak_scaling(spark, [-(-keys.count() // 8)], [4, 8], [1, 2], repeat=5, keys=keys)


@query()
def q122c_slowdown(spark, folder):
    return workloads.slowdown(_customer_metrics(spark, folder))


@query()
def q122d_fluctuation(spark, folder):
    return workloads.fluctuation(_customer_metrics(spark, folder))


@query()
def q123_phases(spark, folder):
    return workloads.phases(read_table(spark, folder, "orders", _OC), TOTAL, P)


@query()
def q124_level_traffic(spark, folder):
    """Messages and volume by level of sorts with one to three levels."""
    return workloads.level_traffic(read_table(spark, folder, "orders", _OC), TOTAL, 64)


@query()
def q125_small_n_traffic(spark, folder):
    """The same with hardly more rows than PEs."""
    return workloads.level_traffic(read_table(spark, folder, "supplier", ["s_suppkey", "s_acctbal"]), key("s_acctbal", ties=("s_suppkey",)), 64)


@query()
def q126_tie_modes(spark, folder):
    return workloads.tie_modes(read_table(spark, folder, "lineitem", ["l_discount", "l_returnflag"]), ["l_discount", "l_returnflag"], P)


@query()
def q89b_imbalance_other_keys(spark, folder):
    out = None
    for table, c, unique in (("events", "value", "event_id"), ("documents", "n_chars", "doc_id")):
        one = workloads.ab_grid(read_table(spark, folder, table, [c, unique]), key(c, ties=(unique,)), unique, 8, [2, 8], [1, 2, 8]).withColumn("key", F.lit(f"{table}.{c}"))
        out = one if out is None else out.unionByName(one)
    return out


@query()
def q127_cost_fit(spark, folder):
    """Start-up and time for each word, fitted to the deliveries of own runs."""
    df, reports = read_table(spark, folder, "orders", _OC), []
    for k in (1, 2, 3):
        report = splitter_sort(df, TOTAL, P, k, measure=True).report
        reports.append(list(report.rows))
        report.release()
    alpha, beta = workloads.cost_fit(reports)
    return spark.createDataFrame([(alpha, beta)], "alpha double, beta double")


# ---- operators around the sorts

@query(f"select (row_number() over (order by {_OO}) - 1)::bigint as rank, o_orderkey from orders")
def q128_merge_layouts(spark, folder):
    df = read_table(spark, folder, "orders", [*_OC, "o_orderstatus"])
    parts = [splitter_sort(df.where(c).select(*_OC), TOTAL, 4, 1) for c in ("o_orderstatus = 'F'", "o_orderstatus <> 'F'")]
    return _ranked(merge_layouts(parts, P), "o_orderkey")


@query(f"select (row_number() over (order by {_OO}) - 1)::bigint as rank, o_orderkey, ((row_number() over (order by {_OO}) * 8 - 1) // (select count(*) from orders))::int as pe from orders")
def q129_append(spark, folder):
    df = read_table(spark, folder, "orders", [*_OC, "o_orderstatus"])
    layout = merge_sort(df.where("o_orderstatus = 'F'").select(*_OC), TOTAL, P, 1)
    return layout.append(df.where("o_orderstatus <> 'F'").select(*_OC)).with_rank().select("rank", "o_orderkey", F.col("_ms_pe").alias("pe"))


@query("""select 'intersect' as op, k from (select o_custkey as k from orders intersect all select c_custkey from customer) union all
select 'except', k from (select o_custkey as k from orders except all select c_custkey from customer) union all select 'union', k from (select o_custkey as k from orders union all select c_custkey from customer)""")
def q130_layout_set_ops(spark, folder):
    layout = splitter_sort(read_table(spark, folder, "orders").select(F.col("o_custkey").alias("k")), key("k"), P, 1)
    other, out = read_table(spark, folder, "customer").select(F.col("c_custkey").alias("k")), None
    for op in ("intersect", "except", "union"):
        one = layout.set_op(other, op).withColumn("op", F.lit(op))
        out = one if out is None else out.unionByName(one)
    return out


@query("select pe::int as pe, ((pe + 1) * n // 8 - pe * n // 8)::bigint as cnt from range(8) r(pe), (select count(*) as n from orders)")
def q131_views(spark, folder):
    """Loads of a merge sort, through the view that a layout makes."""
    merge_sort(read_table(spark, folder, "orders", _OC), TOTAL, P, 1).views()
    return spark.sql("select pe, cnt from ms_loads")


@query("select greatest(0, least(17, floor(16 * (o_totalprice - 0.0) / (500000.0 - 0.0)) + 1))::bigint as bucket, count(*)::bigint as n from orders group by 1")
def q132_equi_width(spark, folder):
    return equi_width(read_table(spark, folder, "orders", _OC), "o_totalprice", 0.0, 500000.0, 16)


@query("select event_id, count(*) over (partition by user_id order by ts range between interval 1 day preceding and current row)::bigint as n from events")
def q133_range_frame(spark, folder):
    t = read_table(spark, folder, "events", ["event_id", "user_id", "ts"])
    return spark.sql("select event_id, count(*) over (partition by user_id order by ts range between interval 1 day preceding and current row) as n from {t}", t=t)


@query("""select how, case when how = 'cross' then (select count(*) from nation, region) else (select count(*) from lineitem join orders on l_orderkey = o_orderkey) end::bigint as n
from (values ('merge'), ('broadcast'), ('shuffle_hash'), ('cross')) v(how)""")
def q134_join_hints(spark, folder):
    line, orders = read_table(spark, folder, "lineitem", ["l_orderkey"]), read_table(spark, folder, "orders", ["o_orderkey"])
    out = read_table(spark, folder, "nation", ["n_name"]).crossJoin(read_table(spark, folder, "region", ["r_name"])).agg(F.count("*").alias("n")).withColumn("how", F.lit("cross"))
    for hint in ("merge", "broadcast", "shuffle_hash"):
        out = out.unionByName(line.join(orders.hint(hint), F.col("l_orderkey") == F.col("o_orderkey")).agg(F.count("*").alias("n")).withColumn("how", F.lit(hint)))
    return out


@query("select l_returnflag, (count(*) filter (where l_linestatus = 'F'))::bigint as \"F\", (count(*) filter (where l_linestatus = 'O'))::bigint as \"O\" from lineitem group by l_returnflag")
def q135_pivot(spark, folder):
    counts = read_table(spark, folder, "lineitem", ["l_returnflag", "l_linestatus"]).groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count()
    return counts.fillna(0)


@query("""select o_orderkey, round(sqrt(o_totalprice), 6) as root, ceil(o_totalprice)::bigint as up, floor(o_totalprice)::bigint as down, round(ln(o_totalprice), 6) as log, (o_orderkey % 7)::bigint as modulo,
greatest(o_custkey, o_orderkey)::bigint as top, (o_orderkey >> 2)::bigint as quarter, xor(o_orderkey, o_custkey)::bigint as mixed from orders""")
def q136_math_funcs(spark, folder):
    k, c, t = F.col("o_orderkey"), F.col("o_custkey"), F.col("o_totalprice")
    return read_table(spark, folder, "orders").select("o_orderkey", F.round(F.sqrt(t), 6).alias("root"), F.ceil(t).alias("up"), F.floor(t).alias("down"), F.round(F.log(t), 6).alias("log"), F.pmod(k, F.lit(7)).alias("modulo"),
                                                      F.greatest(c, k).alias("top"), F.shiftright(k, 2).alias("quarter"), k.bitwiseXOR(c).alias("mixed"))


@query("select l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) as median from lineitem group by l_returnflag")
def q137_grouped_median(spark, folder):
    from tiersort.functions.udfs import median_of

    return read_table(spark, folder, "lineitem", ["l_returnflag", "l_extendedprice"]).groupBy("l_returnflag").agg(F.round(median_of("l_extendedprice"), 4).alias("median"))


@query("select fmt, count(*)::bigint as n, sum(o_orderkey)::bigint as keys, sum(round(o_totalprice * 100)::bigint)::bigint as cents from orders, (values ('csv'), ('json'), ('orc'), ('parquet')) v(fmt) group by fmt")
def q138_formats(spark, folder):
    """A table written as many files of each format, and read again."""
    df, out = read_table(spark, folder, "orders", _OC), None
    for fmt in ("csv", "json", "orc", "parquet"):
        path = scratch(spark, "formats")
        write_sorted(splitter_sort(df, TOTAL, 4, 1), f"{path}/orders.{fmt}", fmt)
        back = read_table(spark, path, "orders", fmt=fmt, schema="o_orderkey long, o_totalprice double")
        one = splitter_sort(back, TOTAL, 4, 1).df.agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("keys"), F.sum(F.round(F.col("o_totalprice") * 100).cast("long")).alias("cents"))
        out = one.withColumn("fmt", F.lit(fmt)) if out is None else out.unionByName(one.withColumn("fmt", F.lit(fmt)))
    return out
