"""URL filter, line dedup and mixing against SQL, on given tables and on awkward ones."""

import random

import pytest
from pyspark.sql import functions as F

from tiersort.llm import lines, mixing, queries, urls
from helpers import DATA
from oracle import rows_of, sql_rows


@pytest.mark.parametrize("name", ["op4_url_filter", "op7_line_dedup", "op9_mixing"])
def test_given_tables(spark, name):
    assert rows_of(queries.QUERIES[name](spark, DATA)) == sql_rows(queries.ORACLES[name], DATA)


def awkward(spark, folder):
    rng = random.Random(4)
    texts = [None, "", "\n\n", "a", "hot line\nb\n\nc", "hot line", "x y z\nhot line\nhot line", "w " * 50000]
    docs = [(i, rng.choice(texts) if i > 8 else texts[i % 8], rng.choice(["s1", "s1", "s1", "ß", "S", None, ""]), "q") for i in range(150)]
    spark.createDataFrame(docs, "doc_id long, text string, source string, lines string").write.parquet(f"{folder}/documents.parquet")
    urls_ = [None, "", "no scheme", "http://A.example.COM/en/7x?z#y", "x://://b", "http://h.net/de/9/a/b/c", "http://example.net#f", "http://example.net/de/8",
             "https://a.org/es/1", "https://a.org/fr/1", "http://www.notcom/en/", "HTTP://x.com?/en/1", "a://b.com/en/\n1"]
    pages = [(i, rng.choice(urls_) if i > 13 else urls_[i % 13], "h") for i in range(200)]
    pages += [(1000 + i, f"http://many.org/{rng.choice(['es', 'fr', chr(97 + i % 26)])}/{i % 7}", None) for i in range(120)]
    spark.createDataFrame(pages, "page_id long, url string, host string").write.parquet(f"{folder}/pages.parquet")


def test_awkward_tables(spark, tmp_path):
    awkward(spark, tmp_path)
    for name in ("op4_url_filter", "op7_line_dedup", "op9_mixing"):
        assert rows_of(queries.QUERIES[name](spark, str(tmp_path))) == sql_rows(queries.ORACLES[name], tmp_path), name


def test_empty_tables(spark, tmp_path):
    for t in ("documents", "pages"):
        spark.read.parquet(f"{DATA}/{t}.parquet").limit(0).write.parquet(f"{tmp_path}/{t}.parquet")
    for name in ("op4_url_filter", "op7_line_dedup", "op9_mixing"):
        assert queries.QUERIES[name](spark, str(tmp_path)).count() == 0


def test_rules_longest_wins(spark):
    rows = [(1, "http://www.example.com/en/71"), (2, "http://www.example.com/en/8"), (3, "http://example.net/de/80"), (4, "http://x.example.net/de/7"), (5, "http://myexample.com/en/7"), (6, "https://a.org/fr/")]
    got = {r.page_id: (r.rule, r.verdict) for r in urls.judge(spark.createDataFrame(rows, "page_id long, url string")).collect()}
    assert got == {1: ("example.com/en/7", "allow"), 2: ("com/en/", "block"), 3: ("example.net/de/8", "block"), 4: ("net/de/", "allow"), 5: ("com/en/", "block"), 6: (None, "allow")}


def test_templates_reject_by_purity(spark):
    rules = [("block", "bad.org", "/shop/a"), ("allow", "bad.org", "/blog/a")]
    rows = [(i, f"http://bad.org/shop/a{i}") for i in range(40)] + [(100 + i, f"http://bad.org/blog/a{i}") for i in range(40)]
    rows += [(200, "http://bad.org/shop/z9"), (201, "http://bad.org/blog/z9"), (202, "http://bad.org/new/z9")]
    got = {r.page_id: r.verdict for r in urls.judge(spark.createDataFrame(rows, "page_id long, url string"), rules).where("rule is null").collect()}
    assert got == {200: "block", 201: "allow", 202: "allow"}


def test_branches_without_evidence_fall_into_their_pool(spark):
    rules = [("block", "bad.org", "/shop/"), ("block", "mixed.org", "/a/b/x/"), ("allow", "mixed.org", "/a/b/y/")]
    rows = [(i, f"http://bad.org/shop/item{i}/view") for i in range(30)]
    rows += [(100 + i, f"http://mixed.org/a/b/x/{i}") for i in range(30)] + [(200 + i, f"http://mixed.org/a/b/y/{i}") for i in range(30)]
    rows += [(300, "http://bad.org/news/1"), (301, "http://bad.org/"), (302, "http://mixed.org/a/b/z/1"), (303, "http://few.org/shop/1"), (304, "http://bad.org/" + "s/" * 3000 + "end"), (305, None)]
    got = {r.page_id: (r.verdict, r.purity) for r in urls.judge(spark.createDataFrame(rows, "page_id long, url string"), rules).where("rule is null").collect()}
    assert {k: v for k, (v, _) in got.items()} == {300: "block", 301: "block", 302: "allow", 303: "allow", 304: "block", 305: "allow"}
    assert abs(got[302][1] - 0.5) < 0.1


def test_many_children_become_one_template(spark):
    rows = [(i, f"http://a.org/{w}/x") for i, w in enumerate("abcdefghijklmnop")] + [(99, "http://a.org/q/x/y")]
    got = {r.page_id: r.template for r in urls.judge(spark.createDataFrame(rows, "page_id long, url string")).collect()}
    assert set(got.values()) == {"/*/x", "/*/x/y"}


def test_more_groups_than_a_driver_holds(spark):
    df = spark.createDataFrame([(f"s{i}", 10 + i, float(x)) for i, x in enumerate([0, 1e-4, 3, 17, 30, 42])], "g string, size long, target double")
    got = mixing.balance_each(df.select("g", "size"), df.select("g", "target"), "g").collect()
    size = {r.g: r.size for r in df.collect()}
    assert all(abs(r.rate * size[r.g] - r.target) <= 1e-12 * max(1, r.target) for r in got) and len(got) == 6


def test_salted_join_equals_broadcast(spark, tmp_path):
    awkward(spark, tmp_path)
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    small, large = (lines.digest(lines.drop_frequent(docs, most_broadcast=n)) for n in (10 ** 6, 0))
    assert rows_of(small) == rows_of(large)
    assert small.agg(F.sum("n_dropped")).first()[0] > 0
    assert set(lines.drop_frequent(docs).columns) == {*docs.columns, "n_lines", "n_dropped"}


def test_copied_pages_stay_whole(spark):
    rows = [(i, f"menu\nown text number {i} of this page\nfooter", "h") for i in range(40)] + [(100 + i, "menu\nthe copied story goes on\nand on", "h") for i in range(20)]
    got = {r.doc_id: r.text for r in lines.drop_frequent(spark.createDataFrame(rows, "doc_id long, text string, source string"), most_cut=0.5).collect()}
    assert got[3] == "own text number 3 of this page" and got[105] == "menu\nthe copied story goes on\nand on"


def test_targets_stop_at_bound(spark):
    df = spark.createDataFrame([("a", 10), ("b", 1000), ("c", 1000), (None, 90)], "source string, source_size long")
    got = {r.source: r.target for r in mixing.targets(df).collect()}
    assert got["a"] == 30 and got[None] == 270 and abs(sum(got.values()) - 2100) < 1e-9
    assert abs(got["b"] / got["c"] - 2) < 1e-12


def test_taken_meets_targets(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    out = mixing.mix(docs)
    sums = out.groupBy("source").agg(F.sum("taken").alias("t"), F.first("target").alias("w")).collect()
    assert all(abs(r.t - r.w) <= 1 for r in sums)
    assert out.where("taken > 3 * size").count() == 0
    assert rows_of(out) == rows_of(mixing.mix(docs.repartition(7)))


def test_newton_meets_two_margins(spark):
    cells = spark.createDataFrame([("a", "x", 50.0), ("a", "y", 20.0), ("b", "x", 10.0), ("b", "y", 40.0)], "s string, l string, size double")
    out = mixing.balance(cells, {"s": {"a": 60.0, "b": 60.0}, "l": {"x": 80.0, "y": 40.0}})
    for c, want in (("s", {"a": 60, "b": 60}), ("l", {"x": 80, "y": 40})):
        got = {r[c]: r.m for r in out.groupBy(c).agg(F.sum(F.col("size") * F.col("rate")).alias("m")).collect()}
        assert all(abs(got[k] - v) < 1e-5 for k, v in want.items())
