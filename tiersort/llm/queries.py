"""Thin queries over the operators, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tiersort.llm import ann, decontaminate, html_text, lines, mixing, pii, quality, repeats, simhash, urls
from tiersort.llm.common import staged, table

Query = Callable[[SparkSession, str], DataFrame]


def op1_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.search(table(spark, sf_dir, "embeddings"), F.col("id") % 50 == 0)


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    fps = staged(simhash.fingerprints(table(spark, sf_dir, "documents"), shingle=3), "fps")
    return simhash.classes(fps, radius=2).select(
        F.col("id").alias("doc_id"), simhash.hex_of(F.col("fp")).alias("fingerprint"), F.col("component").alias("component_id"))


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.digest(decontaminate.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")))


def op3_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.digest(repeats.repeated(table(spark, sf_dir, "documents"), length=50))


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge(table(spark, sf_dir, "pages"))


def op5_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(table(spark, sf_dir, "pages"))


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.personal_data(table(spark, sf_dir, "documents")).withColumnRenamed("id", "doc_id")


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lines.digest(lines.drop_frequent(table(spark, sf_dir, "documents")))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).drop("source")


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")).withColumnRenamed("id", "doc_id")


QUERIES: dict[str, Query] = {"op1_ann": op1_ann, "op2_simhash": op2_simhash, "op3_repeats": op3_repeats, "op4_url_filter": op4_url_filter, "op5_html_text": op5_html_text, "op6_pii": op6_pii, "op7_line_dedup": op7_line_dedup,
                             "op8_decontaminate": op8_decontaminate, "op9_mixing": op9_mixing, "op10_quality": op10_quality}
ORACLES: dict[str, str] = {"op4_url_filter": urls.ORACLE, "op7_line_dedup": lines.ORACLE, "op9_mixing": mixing.ORACLE}
