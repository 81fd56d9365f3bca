import numpy as np
from pyspark.sql import functions as F

from tiersort.llm import quality as q
from tiersort.llm.queries import QUERIES
from helpers import DATA, plain_verdicts

LARGER = "/root/testdata/sf0.1"


def test_held_out_accuracy(spark):
    docs, labels = spark.read.parquet(f"{LARGER}/documents.parquet"), spark.read.parquet(f"{LARGER}/labels.parquet")
    out = q.judge(docs, labels.where("doc_id % 2 = 0")).join(labels.where("doc_id % 2 = 1").toDF("id", "good", "toxic"), "id").cache()
    assert out.count() > 1500
    clean = out.where("good = 1 and toxic = 0")
    assert clean.where("keep").count() >= 0.995 * clean.count()
    for bad in ("good = 0", "toxic = 1"):
        assert out.where(bad).where("not keep").count() >= 0.95 * out.where(bad).count()


def test_edge_rows(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet").select("doc_id", "text", "source", "lang")
    odd = spark.createDataFrame([(-1, None, None, None), (-2, "", "x", None), (-2, "", "x", None), (-3, " \n", "", ""), (-4, "word " * 100000, None, "en")], docs.schema)
    labels = spark.read.parquet(f"{DATA}/labels.parquet")
    twice = labels.unionByName(labels.limit(20)).unionByName(spark.createDataFrame([(None, 1, 0), (0, None, 1), (-1, 0, 0)], labels.schema))
    out = q.judge(docs.unionByName(odd).withColumn("host", F.lit("clash")), twice)
    assert out.count() == docs.count() + 5
    got = {r.id: r.keep for r in out.where("id < 0").collect()}
    assert not got[-1] and not got[-2] and not got[-3]
    assert q.judge(docs.limit(0), labels).count() == 0
    assert q.judge(docs, labels.limit(0)).where("keep").count() == docs.count()  # nothing to learn from


def test_sites_are_shrunk(spark):
    rows = [("big", "a", 3.0)] * 400 + [("low", "a", -3.0)] * 400 + [("tiny", "a", -3.0)]
    df = spark.createDataFrame([(i, h, p, g, -20.0) for i, (h, p, g) in enumerate(rows)], "id long, host string, path string, good double, bad double")
    site = {rows[r.id][0]: r.site_quality for r in q.combined(df).collect()}
    assert site["low"] < site["tiny"] < site["big"]


def test_query_matches_plain_version(spark):
    docs, labels = spark.read.parquet(f"{DATA}/documents.parquet"), spark.read.parquet(f"{DATA}/labels.parquet")
    model = q.fit(q.sample(docs, labels, "doc_id", "text", q.MOST_LABELS))
    rows = [(r.doc_id, r.source, r.lang, *model.evidence(r.text)) for r in docs.collect()]
    want = plain_verdicts(rows)
    got = sorted((r.doc_id, r.quality, r.toxicity, r.keep) for r in QUERIES["op10_quality"](spark, DATA).collect())
    assert len(got) == len(want) == docs.count()
    for g, w in zip(got, want):
        assert g[0] == w[0] and abs(g[1] - w[1]) < 3e-6 and abs(g[2] - w[2]) < 3e-6 and g[3] == w[3]


def test_repeated_label_ids_and_clashing_columns(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    labels = spark.read.parquet(f"{DATA}/labels.parquet")
    twice = docs.unionByName(docs.withColumn("text", F.lit("another text of the same id"))).withColumns({"_id": F.lit(1), "quality": F.lit("x"), "l": F.lit(2)})
    few = [q.sample(twice.repartition(n), labels, "doc_id", "text", 50).orderBy("id").collect() for n in (2, 7)]
    assert few[0] == few[1] and len({r.id for r in few[0]}) == len(few[0]) == 50


def test_logistic_parts_classes():
    rng = np.random.default_rng(0)
    x = np.c_[np.ones(400), rng.normal(size=(400, 2))]
    y = (x @ [0.5, 2, -1] > 0).astype(float)
    assert ((x @ q.logistic(x, y) > 0) == (y > 0)).mean() > 0.98
