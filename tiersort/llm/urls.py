"""URL filter: explicit rules first, then a tree of path templates for each host.

Pages that a rule decides are the labelled ones. A path's segments, all of
them, stand in a tree below its host. Segments with a digit or of over 24
characters become wildcards, and so do the children of a node with more than
``most_children`` different ones (twice, as wildcards bring subtrees together).
On every level, sibling branches whose labelled share of blocked pages doesn't
differ significantly from their pool's are merged: they are judged by their
labelled pages together. A branch without labelled pages has no evidence
against its pool and falls into it.

A template's purity is its branch's blocked share, shrunk towards the purity of
the node above, and so on up to the host's, which is shrunk towards the global
share. It is rejected if the purity reaches a bound and rests on enough
labelled pages: those of the lowest branch on its path that has any, or else of
the host. All steps after the first aggregation (partial sums for each host and
typed path) run over counts, not pages; nodes are named by hashes of the
segments up to them, and only DataFrame functions are used.

A null url, or one without ``://``, has empty host and path; no rule fits and
the empty template of the empty host decides (never labelled: allow). Repeated
pages count each. Urls of any length are read whole. An empty table gives no
row; other columns are ignored. The longest rule wins, and of equally long ones
the first in string order.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tiersort.llm.common import lower_ascii

#: The rules of the contract, as (verdict, host, path).
RULES = [("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/")]


def parts(url: Column) -> tuple[Column, Column]:
    pattern = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    u = F.coalesce(url, F.lit(""))
    return lower_ascii(F.regexp_extract(u, pattern, 1)), F.regexp_extract(u, pattern, 2)


def fitting(host: Column, path: Column, rules: list[tuple[str, str, str]]) -> Column:
    """Struct (rule, verdict) of the longest rule that fits, or null."""
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for verdict, h, p in sorted(rules, key=lambda r: (-len(r[1] + r[2]), r[1] + r[2]), reverse=True):
        fits = ((host == h) | F.endswith(host, F.lit("." + h))) & F.startswith(path, F.lit(p))
        out = F.when(fits, F.struct(F.lit(h + p).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def _typed(segment: Column) -> Column:
    return F.when(segment.rlike("[0-9]") | (F.length(segment) > 24), F.lit("*")).otherwise(segment)


def _above(segment: str) -> Column:
    """Name of the node above: a hash over the segments before this one and their places."""
    before = Window.partitionBy("a", "b").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    return F.coalesce(F.bit_xor(F.xxhash64("pos", segment)).over(before), F.lit(0).cast("long"))


def templates(paths: DataFrame, most_children: int = 12, z: float = 2.0, weight: float = 8.0) -> DataFrame:
    """Rows (a, b, template, purity, evidence) for rows (a, b, host, segments, labelled, blocked), one for each host and typed path."""
    steps = paths.select("a", "b", "host", "labelled", "blocked", F.posexplode("segments").alias("pos", "s"))
    for _ in range(2):  # the children of a node with too many of them are one wildcard
        steps = steps.withColumn("up", _above("s"))
        children = steps.select("host", "up", "pos", "s").distinct().groupBy("host", "up", "pos").agg((F.count("*") > most_children).alias("many"))
        steps = steps.join(children, ["host", "up", "pos"]).withColumn("s", F.when(F.col("many"), F.lit("*")).otherwise(F.col("s"))).drop("many")
    steps = steps.withColumn("up", _above("s"))
    nodes = steps.groupBy("host", "up", "pos", "s").agg(F.sum("labelled").alias("tn"), F.sum("blocked").alias("tb"))
    pools = nodes.groupBy("host", "up", "pos").agg(F.sum("tn").alias("pn"), F.sum("tb").alias("pb"))
    share = F.col("pb") / F.col("pn")
    gap = F.col("tb") / F.col("tn") - share
    alike = F.when(F.col("tn") > 0, gap * gap * F.col("tn") <= z * z * share * (1 - share) + 1e-12).otherwise(F.lit(True))
    known = nodes.join(pools, ["host", "up", "pos"]).withColumn("alike", F.when(F.col("pn") > 0, alike).otherwise(F.lit(True)))
    merged = known.where("alike").groupBy("host", "up", "pos").agg(F.sum("tn").alias("mn"), F.sum("tb").alias("mb"))
    known = known.join(merged, ["host", "up", "pos"], "left").select(
        "host", "up", "pos", "s", F.when(F.col("alike"), F.col("mn")).otherwise(F.col("tn")).alias("n"), F.when(F.col("alike"), F.col("mb")).otherwise(F.col("tb")).alias("k"))
    lists = steps.join(known, ["host", "up", "pos", "s"]).groupBy("a", "b").agg(F.sort_array(F.collect_list(F.struct("pos", "s", "n", "k"))).alias("way"))
    hosts = paths.groupBy("host").agg(F.sum("labelled").alias("hn"), F.sum("blocked").alias("hb"))
    total = hosts.agg(F.coalesce(F.try_divide(F.sum("hb"), F.sum("hn")), F.lit(0.0)).alias("world"))
    t = paths.select("a", "b", "host").join(lists, ["a", "b"], "left").join(hosts, "host").crossJoin(F.broadcast(total))  # one row
    t = t.withColumn("way", F.coalesce("way", F.array().cast(lists.schema["way"].dataType)))
    site = (F.col("hb") + weight * F.col("world")) / (F.col("hn") + weight)
    return t.select("a", "b", F.concat(F.lit("/"), F.array_join(F.col("way.s"), "/")).alias("template"),
                    F.aggregate("way", site, lambda p, x: (x["k"] + weight * p) / (x["n"] + weight)).alias("purity"),
                    F.aggregate("way", F.col("hn"), lambda n, x: F.when(x["n"] > 0, x["n"]).otherwise(n)).alias("evidence"))


def judge(pages: DataFrame, rules: list[tuple[str, str, str]] = RULES, id_col: str = "page_id", url_col: str = "url",
          bound: float = 0.8, enough: int = 5) -> DataFrame:
    """Rows (page_id, host, path, rule, verdict, template, purity)."""
    host, path = parts(F.col(url_col))
    rows = pages.select(F.col(id_col).alias("page_id"), host.alias("host"), path.alias("path"))
    rows = rows.withColumns({"fit": fitting(F.col("host"), F.col("path"), rules), "segments": F.transform(F.filter(F.split("path", "/"), lambda x: x != ""), _typed)})
    rows = rows.withColumns({"a": F.xxhash64("host", "segments"), "b": F.xxhash64(F.lit(1), "segments", "host")})
    # every hash stands for one host and typed path
    paths = rows.groupBy("a", "b").agg(F.first("host").alias("host"), F.first("segments").alias("segments"), F.count("fit").alias("labelled"),
                                       F.count(F.when(F.col("fit.verdict") == "block", 1)).alias("blocked"))
    method = F.when((F.col("purity") >= bound) & (F.col("evidence") >= enough), F.lit("block")).otherwise(F.lit("allow"))
    return rows.join(templates(paths), ["a", "b"], "left").select(
        "page_id", "host", "path", F.col("fit.rule").alias("rule"), F.coalesce("fit.verdict", method).alias("verdict"),
        "template", F.round("purity", 9).alias("purity"))


ORACLE = r"""
with u as (select page_id, translate(regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
                  regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 2) as path from pages),
r(verdict, rh, rp) as (values ('block', 'com', '/en/'), ('allow', 'example.com', '/en/7'), ('allow', 'net', '/de/'), ('block', 'example.net', '/de/8'), ('block', 'org', '/es/')),
w as (select host, path, arg_max(struct_pack(rule := rh || rp, verdict := verdict), length(rh || rp)) as f
      from (select distinct host, path from u) join r on (host = rh or ends_with(host, '.' || rh)) and starts_with(path, rp) group by host, path),
p as (select u.*, f.rule as rule, f.verdict as fv, list_transform(list_filter(string_split(path, '/'), lambda x: x <> ''), lambda x: case when regexp_matches(x, '[0-9]') or length(x) > 24 then '*' else x end) as g
      from u left join w using (host, path)),
j as (select host, g, count(rule) as labelled, count(*) filter (where fv = 'block') as blocked from p group by all),
e as (select *, unnest(generate_series(1, len(g))) as pos from j),
c1 as (select host, g[1:pos - 1] as up, pos, count(distinct g[pos]) > 12 as many from e group by all),
s1 as (select e.host, g, labelled, blocked, list(case when many then '*' else g[e.pos] end order by e.pos) as h from e join c1 on e.host = c1.host and e.pos = c1.pos and g[1:e.pos - 1] = up group by all),
e1 as (select *, unnest(generate_series(1, len(h))) as pos from s1),
c2 as (select host, h[1:pos - 1] as up, pos, count(distinct h[pos]) > 12 as many from e1 group by all),
s2 as (select e1.host, g, labelled, blocked, list(case when many then '*' else h[e1.pos] end order by e1.pos) as t from e1 join c2 on e1.host = c2.host and e1.pos = c2.pos and h[1:e1.pos - 1] = up group by all),
e2 as (select *, unnest(generate_series(1, len(t))) as pos from s2),
n as (select host, t[1:pos - 1] as up, t[pos] as s, sum(labelled) as tn, sum(blocked) as tb from e2 group by all),
o as (select *, sum(tn) over (partition by host, up) as pn, sum(tb) over (partition by host, up) as pb from n),
k as (select *, case when pn > 0 and tn > 0 then (tb / tn - pb / pn) * (tb / tn - pb / pn) * tn <= 4.0 * (pb / pn) * (1 - pb / pn) + 1e-12 else true end as alike from o),
m as (select host, up, s, case when alike then sum(tn) filter (where alike) over (partition by host, up) else tn end as n,
             case when alike then sum(tb) filter (where alike) over (partition by host, up) else tb end as b from k),
hs as (select host, sum(labelled) as hn, sum(blocked) as hb from j group by host),
wd as (select coalesce(sum(hb) / nullif(sum(hn), 0), 0) as world from hs),
way as (select e2.host, g, t, list(m.n::double order by pos) as ns, list(m.b::double order by pos) as bs from e2 join m on e2.host = m.host and t[1:pos - 1] = up and t[pos] = s group by all),
base as (select j.host, j.g, coalesce(t, []) as t, coalesce(ns, []) as ns, coalesce(bs, []) as bs, hn, (hb + 8.0 * world) / (hn + 8.0) as site from j join hs using (host) cross join wd left join way on j.host = way.host and j.g = way.g),
z as (select host, g, '/' || array_to_string(t, '/') as template,
             list_reduce(list_prepend({'n': 0.0, 'v': site}, list_transform(generate_series(1, len(ns)), lambda i: {'n': ns[i], 'v': bs[i]})), lambda acc, x: {'n': 0.0, 'v': (x['v'] + 8.0 * acc['v']) / (x['n'] + 8.0)})['v'] as purity,
             list_reduce(list_prepend(hn::double, ns), lambda acc, x: case when x > 0 then x else acc end) as evidence from base)
select page_id, p.host, path, rule, coalesce(fv, case when purity >= 0.8 and evidence >= 5 then 'block' else 'allow' end) as verdict, template, round(purity, 9) as purity
from p join z on p.host = z.host and p.g = z.g"""
