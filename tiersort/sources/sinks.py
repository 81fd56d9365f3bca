"""Sorted layouts as files, and back."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tiersort.functions.keys import KeySpec


def scratch(spark: SparkSession, tag: str = "layout") -> str:
    """A new path in the folder that driver and executors share (a temporary one only for a session on one machine that names none)."""
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None) or (held.get() if held.isDefined() else None)
    if not named:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        named = tempfile.mkdtemp(prefix="tiersort-")
        spark.sparkContext.setCheckpointDir(named)
    return f"{named.rstrip('/')}/{tag}-{uuid.uuid4().hex}"


def staged(df: DataFrame, tag: str = "level") -> DataFrame:
    """``df`` written to the shared folder and read again: whatever numbered its rows is fixed from then on."""
    path = scratch(df.sparkSession, tag)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._staged_at = path
    return out


def discard(df: DataFrame) -> None:
    """Deletes the files of a staged table."""
    path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(df._staged_at)
    path.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def write_sorted(layout, path: str, fmt: str = "parquet") -> None:
    """A folder for each PE with its rows in order; footers' ranges don't overlap, so readers skip files. Counts and fences stand beside."""
    layout.stats.coalesce(1).write.mode("overwrite").json(f"{path}.manifest")
    layout.df.drop("_ms_row").withColumn("pe", F.col("_ms_pe")).write.mode("overwrite").partitionBy("pe").format(fmt).save(path)


def write_bucketed(layout, name: str, buckets: int) -> None:
    """A table of ``buckets`` buckets by the key's columns, each sorted: joins on them need no exchange."""
    cols = list(layout.key.cols)
    layout.df.drop("_ms_row", "_ms_pe").write.mode("overwrite").bucketBy(buckets, *cols).sortBy(*cols).saveAsTable(name)


def write_metrics(metrics: DataFrame, path: str) -> None:
    """Metric rows as JSON lines, added to those that are there."""
    metrics.coalesce(1).write.mode("append").json(path)


def read_sorted(spark: SparkSession, path: str, key: KeySpec, p: int, fmt: str = "parquet"):
    from tiersort.operators.layout import SortedLayout

    df = spark.read.format(fmt).load(path)  # its folders by PE are skipped where ranges don't overlap
    return SortedLayout(df.drop("pe").repartitionById(p, F.col("_ms_pe")).sortWithinPartitions("_ms_pe", *key.order()), key, p)


def measure_only(df: DataFrame) -> None:
    """Computes everything and keeps nothing."""
    df.write.format("noop").mode("overwrite").save()
