"""Line dedup by site-relative frequency.

A line's share is the number of its host's pages that hold it over the number
of the host's pages. Lines over the ratio go. Only DataFrame functions are
used. Lines are counted by a 96-bit hash, once for each page, with partial
counts before the exchange; a host with a third of all pages is no hot task.

A host's frequent lines number at most (mean lines of a page) / ratio. They
go to the pages in a broadcast as long as all of them are within a checked
bound; beyond it in a join whose host keys are salted.

Null text stays null, empty lines stay where they are, a null host is a host
of its own, repeated pages count each. Ties at the ratio stay. A page of which
more than ``most_cut`` of its characters would go isn't content in a frame but
a copy of other pages; it stays whole, for near-duplicate stages to judge. An
empty table gives no row, further columns are passed on.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tiersort.llm.common import staged

SALTS = 32


def _key(line: Column) -> Column:
    return F.struct(F.xxhash64(line).alias("a"), F.hash(line).alias("b"))


def frequent(pages: DataFrame, text_col: str = "text", host_col: str = "source", ratio: float = 0.05, least: int = 5) -> DataFrame:
    """Rows (host, lines): keys of lines on more than ``ratio`` of the host's pages, and on ``least`` at least."""
    lines = F.array_distinct(F.transform(F.filter(F.split(F.coalesce(text_col, F.lit("")), "\n"), lambda x: F.trim(x) != ""), lambda x: _key(x)))
    keyed = pages.select(F.col(host_col).alias("host"), F.explode(lines).alias("k"))
    counts = keyed.groupBy("host", "k.a", "k.b").agg(F.count("*").alias("n")).where(F.col("n") >= least)
    totals = pages.groupBy(F.col(host_col).alias("of")).agg(F.count("*").alias("total"))
    over = counts.join(totals, F.col("host").eqNullSafe(F.col("of"))).where(F.col("n") > ratio * F.col("total"))
    return over.groupBy("host").agg(F.sort_array(F.collect_list(F.struct("a", "b"))).alias("lines"))


def drop_frequent(pages: DataFrame, text_col: str = "text", host_col: str = "source", ratio: float = 0.05, least: int = 5,
                  most_cut: float = 1.0, most_broadcast: int = 200_000) -> DataFrame:
    """``pages`` with the text's frequent lines left out, and ``n_lines``, ``n_dropped`` (long)."""
    found = staged(frequent(pages, text_col, host_col, ratio, least), "frequent")
    held = found.agg(F.sum(F.size("lines"))).first()[0] or 0
    found = found.toDF("_ts_host", "_ts_lines")
    if held <= most_broadcast:
        joined = pages.join(F.broadcast(found), F.col(host_col).eqNullSafe(F.col("_ts_host")), "left")
    else:
        salted = found.withColumn("_ts_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        joined = pages.withColumn("_ts_of", F.pmod(F.xxhash64(text_col), F.lit(SALTS)).cast("int")).join(
            salted, F.col(host_col).eqNullSafe(F.col("_ts_host")) & (F.col("_ts_of") == F.col("_ts_salt")), "left").drop("_ts_of", "_ts_salt")
    split = F.split(text_col, "\n")
    stays = F.filter(split, lambda x: (F.trim(x) == "") | ~F.array_contains(F.coalesce("_ts_lines", F.array().cast("array<struct<a:bigint,b:int>>")), _key(x)))
    out = joined.withColumn("_ts_all", split).withColumn("_ts_kept", stays)
    size = lambda c: F.aggregate(c, F.lit(0), lambda s, x: s + F.length(F.trim(x)))
    cut = size(F.col("_ts_all")) - size(F.col("_ts_kept"))
    spare = (size(F.col("_ts_kept")) == 0) | (cut > most_cut * size(F.col("_ts_all")))
    out = out.withColumn("_ts_kept", F.when(spare, F.col("_ts_all")).otherwise(F.col("_ts_kept")))
    return out.withColumns({
        "n_lines": F.coalesce(F.size("_ts_all"), F.lit(0)).cast("long"), "n_dropped": F.coalesce(F.size("_ts_all") - F.size("_ts_kept"), F.lit(0)).cast("long"),
        text_col: F.array_join("_ts_kept", "\n")}).select(*pages.columns, "n_lines", "n_dropped")


def digest(out: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    return out.select(F.col(id_col).alias("doc_id"), "n_lines", "n_dropped", F.sha2(F.coalesce(text_col, F.lit("")).cast("binary"), 256).alias("kept_sha256"))


ORACLE = r"""
with p as (select doc_id, source, string_split(text, chr(10)) as ls from documents),
l as (select source, k, count(*) as n from (select source, unnest(list_distinct(list_filter(ls, lambda x: trim(x) <> ''))) as k from p) group by all),
t as (select source, count(*) as total from p group by source),
f as (select l.source, list(k) as bad from l join t on l.source is not distinct from t.source where n >= 5 and n > 0.05::double * total group by 1),
k as (select p.*, list_filter(ls, lambda x: trim(x) = '' or not list_contains(coalesce(bad, []::varchar[]), x)) as good
      from p left join f on p.source is not distinct from f.source),
g as (select doc_id, ls, case when len(list_filter(good, lambda x: trim(x) <> '')) = 0 then ls else good end as good from k)
select doc_id, coalesce(len(ls), 0)::bigint as n_lines, coalesce(len(ls) - len(good), 0)::bigint as n_dropped,
       sha256(coalesce(array_to_string(good, chr(10)), '')) as kept_sha256 from g"""
