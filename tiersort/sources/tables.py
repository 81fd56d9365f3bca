"""Readers and generators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tiersort.functions.mixing import h, random64


def read_table(spark: SparkSession, folder: str, name: str, cols: list[str] | None = None, where: str | None = None, fmt: str = "parquet", **options) -> DataFrame:
    """A table of a folder; columns and filter reach the scan."""
    path, schema = f"{folder}/{name}.{fmt}", options.pop("schema", None)
    reader = spark.read.format(fmt).options(**options)
    df = (reader.schema(schema) if schema else reader).load(path)
    df = df.where(where) if where else df
    return df.select(*cols) if cols else df


def rand64(spark: SparkSession, n: int, seed: int = 0) -> DataFrame:
    return spark.range(n).select("id", random64(F.col("id"), seed).alias("key"))


def rate_keys(spark: SparkSession, rows_per_second: int = 100, seed: int = 0) -> DataFrame:
    """An endless stream (id, ts, key) of random 64-bit keys."""
    rows = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return rows.select(F.col("value").alias("id"), F.col("timestamp").alias("ts"), random64(F.col("value"), seed).alias("key"))


def rec100(spark: SparkSession, n: int, seed: int = 0) -> DataFrame:
    """Records of 100 bytes with keys of 10."""
    digest = F.unhex(F.sha2(F.concat_ws(":", F.lit(seed).cast("string"), F.col("id").cast("string")), 512))
    return spark.range(n).select("id", F.substring(digest, 1, 10).alias("key"), F.substring(F.concat(digest, digest), 11, 90).alias("payload"))


def _grid(spark: SparkSession, p: int, r: int) -> DataFrame:
    return spark.range(p * r).select((F.col("id") % p).cast("int").alias("pe"), F.expr(f"cast(id div {p} as int)").alias("grp"))


def _ranged(df: DataFrame, p: int, r: int) -> DataFrame:
    """Piece sizes with the destination groups' PEs; groups are named by their first PE."""
    base, end = F.expr(f"cast(grp * {p} div {r} as int)"), F.expr(f"cast((grp + 1) * {p} div {r} as int)")
    return df.select("pe", base.alias("grp"), "size", base.alias("base"), (end - base).alias("q"))


def tiny_run(spark: SparkSession, p: int, r: int, start: int, length: int, large: int = 1000) -> DataFrame:
    """Pieces where the PEs [start, start + length) hold one element of group 0 each, and all else is large."""
    size = F.when((F.col("grp") == 0) & F.col("pe").between(start, start + length - 1), F.lit(1)).otherwise(F.lit(large))
    return _ranged(_grid(spark, p, r).withColumn("size", size.cast("long")), p, r)


def few_large(spark: SparkSession, p: int, r: int, large: int = 1000) -> DataFrame:
    """Pieces of which all but p/r in each group hold one element."""
    size = F.when(h(F.col("pe") * r + F.col("grp")) % r == 0, F.lit(large)).otherwise(F.lit(1))
    return _ranged(_grid(spark, p, r).withColumn("size", size.cast("long")), p, r)


def pieces_of(df: DataFrame, p: int, r: int, pe, grp) -> DataFrame:
    """Pieces of a table whose rows say their source PE and destination group."""
    counts = df.select(pe.cast("int").alias("pe"), grp.cast("int").alias("grp")).groupBy("pe", "grp").agg(F.count("*").alias("size"))
    return _ranged(counts, p, r)
