"""A corpus pipeline: quality, boilerplate lines, near-duplicates, benchmark leaks, mixture.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame, which is
written as Parquet in the shared folder and read again as the next one's
``docs``. All but the last keep the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tiersort.llm import decontaminate, lines, mixing, quality, simhash
from tiersort.llm.common import row_key, staged, table


def _apart(docs: DataFrame, *reserved: str) -> tuple[DataFrame, dict[str, str]]:
    """``docs`` with columns of reserved names renamed, and the way back."""
    back = {f"_own_{i}_": c for i, c in enumerate(docs.columns) if c.lower() in reserved}
    return docs.withColumnsRenamed({c: k for k, c in back.items()}), back


def _sized(docs: DataFrame, columns: list[str]) -> DataFrame:
    """The columns of ``documents``, with ``n_chars`` of the text as it now is."""
    if "n_chars" in columns:
        docs = docs.withColumn("n_chars", F.length("text").cast("long"))
    return docs.select(*columns)


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier keeps (good quality, not toxic). Rows are told apart by all their columns, so null and repeated ids stay."""
    mine, back = _apart(docs, "_row", "id")
    rows = mine.withColumn("_row", F.to_json(row_key(mine)))
    kept = quality.judge(rows, table(spark, sf_dir, "labels"), row_col="_row").where("keep").select("id").distinct()
    return rows.join(kept, rows["_row"] == kept["id"], "left_semi").drop("_row").withColumnsRenamed(back).select(*docs.columns)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the boilerplate lines of their source; one with nothing else stays whole."""
    mine, back = _apart(docs, "n_lines", "n_dropped")
    return _sized(lines.drop_frequent(mine).drop("n_lines", "n_dropped").withColumnsRenamed(back), docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near-duplicates the document with the smallest id (null ids last; of equal ids the row with the smallest key).

    Links are texts that share 0.8 of their five-word shingles; candidates come
    from bands of minima and from SimHash fingerprints within 2 bits.
    """
    mine, back = _apart(docs, "_row", "h1", "h2", "class", "f")
    h1, h2 = simhash.text_key("text")
    rows = mine.withColumns({"_row": row_key(mine), "h1": h1, "h2": h2})
    named = rows.select("doc_id", "_row", "h1", "h2").join(simhash.near_texts(mine), ["h1", "h2"])
    first = named.groupBy("class").agg(F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "_row")).alias("f")).select("f._row")
    return rows.join(first, "_row", "left_semi").dropDuplicates(["_row"]).drop("_row", "h1", "h2").withColumnsRenamed(back).select(*docs.columns)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the words of benchmark items; an item of under ten words is searched as a whole."""
    return _sized(decontaminate.cut(docs, table(spark, sf_dir, "benchmark")), docs.columns)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with the words that the mix takes of them; those without any go. Its columns replace others of their names."""
    own = [c for c in docs.columns if c.lower() not in ("size", "source_size", "target", "taken")]
    mine, back = _apart(docs.select(*own), "_row")
    rows = staged(mine.withColumn("_row", F.monotonically_increasing_id()), "numbered")  # written once, so the numbers stay
    taken = mixing.mix(rows, carry=("_row",)).where("taken > 0").select("_row", "size", "source_size", "target", "taken")
    return rows.join(taken, "_row").drop("_row").withColumnsRenamed(back)


STAGES = [("quality classifier", quality_filter), ("line dedup", line_dedup), ("SimHash near-dedup", near_dedup),
          ("benchmark decontamination", decontamination), ("mixing sources", mixture)]

#: The classifier, the near-duplicates and the phrase search can't be written in SQL; the tests run plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = staged(stage(spark, docs, sf_dir), f"stage{k}")
    return docs
