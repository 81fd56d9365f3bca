"""The pipeline's stages, each on what the one before kept."""

import sys
from pathlib import Path

import pytest
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).resolve().parents[2]))
corpus_pipeline = pytest.importorskip("corpus_pipeline")

from helpers import DATA, plain_contamination, plain_cut, plain_lines, plain_near, plain_verdicts  # noqa: E402
from oracle import sql_rows  # noqa: E402
from tiersort.llm import mixing, quality  # noqa: E402
from tiersort.llm.common import staged  # noqa: E402


@pytest.fixture(scope="module")
def stages(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    out = [docs]
    for name, f in corpus_pipeline.STAGES:
        out.append(staged(f(spark, out[-1], DATA), "test"))
    return out


def test_columns_and_counts(stages):
    assert [n for n, _ in corpus_pipeline.STAGES][2] == "SimHash near-dedup" and len(corpus_pipeline.STAGES) == 5
    for df in stages[:-1]:
        assert df.columns == stages[0].columns
    counts = [df.count() for df in stages]
    assert counts == sorted(counts, reverse=True) and counts[-1] > 0.3 * counts[0]


def test_each_stage_does_its_part(spark, stages):
    docs, good, lined, distinct, clean, mixed = stages
    labels = spark.read.parquet(f"{DATA}/labels.parquet")
    fine = labels.where("quality = 1 and toxic = 0").join(docs, "doc_id", "left_semi")
    assert good.join(fine, "doc_id", "left_semi").count() >= 0.99 * fine.count()
    assert good.join(labels.where("quality = 0 or toxic = 1"), "doc_id", "left_semi").count() <= 0.05 * labels.where("quality = 0 or toxic = 1").count()
    assert lined.count() == good.count() and lined.agg(F.sum("n_chars")).first()[0] <= good.agg(F.sum("n_chars")).first()[0]
    assert distinct.select("text").where("text <> ''").distinct().count() == distinct.where("text <> ''").count()
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{DATA}/benchmark.parquet").collect() if len((r.text or "").split()) >= 10]
    found = plain_contamination([(r.doc_id, r.text) for r in clean.collect()], items)
    assert not any(x[4] for x in found.values())
    off = mixed.groupBy("source").agg(F.sum("taken").alias("t"), F.first("target").alias("w")).where(F.abs(F.col("t") - F.col("w")) > 1)
    assert off.count() == 0
    assert all(r.n_chars == len(r.text) for r in clean.collect())


def test_empty_documents(spark, tmp_path):
    for t in ("documents", "labels", "benchmark"):
        spark.read.parquet(f"{DATA}/{t}.parquet").limit(0).write.parquet(f"{tmp_path}/{t}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_short_pages_lose_their_frame(spark):
    frame = "\n".join(f"menu entry number {i} of this site" for i in range(10))
    rows = [(i, f"{frame}\nown line {i}", "en", "s", 0) for i in range(20)] + [(20, frame, "en", "s", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    got = {r.doc_id: r.text for r in corpus_pipeline.line_dedup(spark, docs, "").collect()}
    assert got == {i: f"own line {i}" for i in range(20)} | {20: frame}


def test_short_items_are_cut(spark, tmp_path):
    spark.createDataFrame([("a", "which river is the longest"), ("b", None), ("c", "")], "item_id string, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    rows = [(1, "He asked: Which river is the longest? Nobody knew.", "en", "s", 0), (2, "which river is long", "en", "s", 0), (3, "Which river is the longest", "en", "s", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    got = {r.doc_id: r.text for r in corpus_pipeline.decontamination(spark, docs, str(tmp_path)).collect()}
    assert got == {1: "He asked: ? Nobody knew.", 2: "which river is long"}


def test_null_and_repeated_ids_stay_apart(spark, tmp_path):
    good = [(r.doc_id, r.text, r.lang, r.source, r.n_chars) for r in spark.read.parquet(f"{DATA}/documents.parquet").join(
        spark.read.parquet(f"{DATA}/labels.parquet").where("quality = 1 and toxic = 0"), "doc_id").where("n_chars > 300").dropDuplicates(["text"]).orderBy("doc_id").limit(40).collect()]
    rows = [(None, *r[1:]) if k < 10 else (7, *r[1:]) if k < 20 else r for k, r in enumerate(good)]
    docs = spark.createDataFrame([*rows, rows[0], rows[12]], "doc_id long, text string, lang string, source string, n_chars long")
    kept = corpus_pipeline.quality_filter(spark, docs, DATA)
    assert kept.where("doc_id is null").count() >= 9 and kept.where("doc_id = 7").count() >= 9
    distinct = staged(corpus_pipeline.near_dedup(spark, docs, DATA), "test")
    alone = corpus_pipeline.near_dedup(spark, spark.createDataFrame(good, docs.schema), DATA).count()
    assert distinct.count() == alone and distinct.where("doc_id is null").count() > 0 and distinct.where("doc_id = 7").count() > 1
    mixed = corpus_pipeline.mixture(spark, distinct, DATA)
    off = mixed.groupBy("source").agg(F.sum("taken").alias("t"), F.first("target").alias("w")).where(F.abs(F.col("t") - F.col("w")) > 1)
    assert off.count() == 0 and mixed.where("doc_id is null").count() > 0


def test_clashing_columns(spark, tmp_path):
    base = spark.read.parquet(f"{DATA}/documents.parquet").where("doc_id < 300")
    odd = ["_row", "id", "h1", "class", "n_lines", "Size", "target", "quality", "_id"]
    docs = staged(base.withColumns({c: F.lit(f"own {c}") for c in odd}), "test")
    for t in ("labels", "benchmark"):
        spark.read.parquet(f"{DATA}/{t}.parquet").write.parquet(f"{tmp_path}/{t}.parquet")
    plain = staged(base, "test")
    for name, f in corpus_pipeline.STAGES:
        docs, plain = staged(f(spark, docs, str(tmp_path)), "test"), staged(f(spark, plain, str(tmp_path)), "test")
        assert docs.count() == plain.count(), name
        for c in odd:
            if c in docs.columns and c not in ("target",):
                assert docs.where(F.col(c) != f"own {c}").count() == 0, (name, c)
    assert docs.schema["target"].dataType.simpleString() == "double" and "Size" not in docs.columns


def test_run_equals_plain_version(spark, tmp_path):
    folder = DATA.replace("sf0.01", "sf0.001")
    docs, labels = spark.read.parquet(f"{folder}/documents.parquet"), spark.read.parquet(f"{folder}/labels.parquet")
    model = quality.fit(quality.sample(docs, labels, "doc_id", "text", quality.MOST_LABELS))
    rows = sorted(docs.select("doc_id", "text", "lang", "source").collect())
    good = {v[0] for v in plain_verdicts([(r.doc_id, r.source, r.lang, *model.evidence(r.text)) for r in rows]) if v[3]}
    rows = [tuple(r) for r in rows if r.doc_id in good]
    rows = [(r[0], t, r[2], r[3]) for r, t in zip(rows, plain_lines([(r[0], r[1], r[3]) for r in rows]))]
    stay = plain_near([r[:2] for r in rows])
    items = [r.text for r in spark.read.parquet(f"{folder}/benchmark.parquet").collect()]
    rows = [(r[0], plain_cut(r[1], items), *r[2:]) for r in rows if r[0] in stay]
    rows = [r for r in rows if r[1] is not None]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    taken = {r[0]: r[3] for r in sql_rows(mixing.ORACLE, tmp_path)}  # columns in the order of their names
    want = sorted((r[0], r[1], taken[r[0]]) for r in rows if taken[r[0]] > 0)
    got = sorted((r.doc_id, r.text, r.taken) for r in corpus_pipeline.run(spark, folder).collect())
    assert got == want and len(want) > 20
