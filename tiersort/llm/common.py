"""What several operators need: tables, staging folders, connected components."""

from __future__ import annotations

import pickle
import tempfile
import uuid
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The white space of the contracts, as a character class for Java and DuckDB.
WORD_BYTES = r"[^\x20\x09-\x0D]+"

#: Makes Spark delete a query's shuffle files at its end, not when its plan is collected as garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Where the session names none, a session on one machine (as in tests) gets a
    temporary one; on a cluster that is an error, as executors could not see it.
    """
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return held.get()
    if not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    made = tempfile.mkdtemp(prefix="tiersort-")
    spark.sparkContext.setCheckpointDir(made)
    return made


def staged(df: DataFrame, tag: str) -> DataFrame:
    """``df`` written to the shared folder and read again.

    It cuts the lineage, survives lost executors and is computed once. The
    write's own shuffle files go when it ends: nothing can read them any more.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/tiersort-{uuid.uuid4().hex}/{tag}"
    before = spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(CLEANUP, before)
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_at = path
    return out


def discard(df: DataFrame) -> None:
    """Deletes the files of a staged table that nothing reads any more."""
    path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(df._staged_at)
    path.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(path.getParent(), True)


def shipped(spark: SparkSession, what: object) -> Callable[[], object]:
    """``what`` broadcast with its class by value; workers call the result to get it, without the repository on their path."""
    box = spark.sparkContext.broadcast(cloudpickle.dumps(what))

    def get() -> object:
        return pickle.loads(box.value)

    return get


def free_names(df: DataFrame, *wanted: str) -> list[str]:
    """Column names like those wanted that ``df`` doesn't use (case aside)."""
    used, out = {c.lower() for c in df.columns}, []
    for name in wanted:
        while name.lower() in used:
            name += "_"
        used.add(name.lower())
        out.append(name)
    return out


def row_key(df: DataFrame) -> Column:
    """128 bits that name a row by all its columns, never null; equal rows share them.

    Flags of nulls are part of it, as the hash passes over null values.
    """
    nulls = [F.col(c).isNull() for c in df.columns]
    cols = [F.col(c) for c in df.columns]
    return F.struct(F.xxhash64(*nulls, *cols).alias("a"), F.xxhash64(F.lit(1), *cols[::-1], *nulls).alias("b"))


def lower_ascii(text: Column) -> Column:
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def word_count(text: Column) -> Column:
    """Number of maximal runs without white space (null: 0), without making an array of them."""
    starts = F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD_BYTES))
    return starts.cast("long")


#: Rows of a key from which on it counts as hot, and the share of all rows from which on it does in larger tables: at most HUB_PARTS keys do.
HUB_ROWS, HUB_PARTS = 1_000, 2_000
#: Rows that one task may have of one key: tables up to this size have no hubs to keep apart.
HUB_TABLE = 1_000_000


def with_least(rows: DataFrame, key: str, value: str, n: int, name: str = "m", alone: bool = True) -> DataFrame:
    """``rows`` with the smallest ``value`` of each ``key``; ``n`` rows at most. Without ``alone``, rows of keys that occur once are left out.

    Minima are aggregated before the exchange. Those of keys with more than
    HUB_ROWS and n / HUB_PARTS rows, HUB_PARTS at most, are broadcast, so the
    rows of a hub stay where they are; the others are joined by key. In tables
    of up to HUB_TABLE rows all are.
    """
    least = rows.groupBy(key).agg(F.min(value).alias(name), F.count("*").alias("_n"))
    if n <= HUB_TABLE:
        return rows.join((least if alone else least.where("_n > 1")).drop("_n"), key)
    bound = max(HUB_ROWS, n // HUB_PARTS)
    held = rows.join(F.broadcast(least.where(F.col("_n") > bound).select(key, F.col(name).alias("_hub"))), key, "left")
    rest = held.where("_hub is null").drop("_hub").join(least.where(F.col("_n").between(1 if alone else 2, bound)).drop("_n"), key)
    return rest.unionByName(held.where("_hub is not null").withColumnRenamed("_hub", name))


def least_joined(n: int, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """For each of ``n`` vertices the smallest that edges (u, v) reach, itself included."""
    low = np.arange(n)
    while True:
        a, b = low[u], low[v]  # hooks the smallest known ones to each other, then follows them to the end
        after = low.copy()
        np.minimum.at(after, np.maximum(a, b), np.minimum(a, b))
        while not np.array_equal(after, further := after[after]):
            after = further
        if np.array_equal(after, low):
            return low
        low = after


def components(edges: DataFrame, src: str = "u", dst: str = "v", few: int = 0) -> DataFrame:
    """Connected components of an undirected edge list: rows (id, component).

    ``component`` is the smallest id that can be reached; ids without an edge
    are not listed. Neighbours are contracted to ever smaller ones (every
    vertex links its larger neighbours to the smallest it knows, then its
    smaller ones), so that the number of rounds grows with the logarithm of a
    component's size and no vertex is collected into one task: minima are
    aggregated before the exchange and hubs' rows aren't exchanged. Each round
    is staged in the shared folder; the one before it is deleted. Up to ``few``
    edges are joined on the driver as arrays instead, to the same result.
    """
    def tidy(df: DataFrame) -> DataFrame:
        return df.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()

    def sign(df: DataFrame) -> tuple:
        return tuple(df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first())

    now = staged(tidy(edges.select(F.col(src).alias("u"), F.col(dst).alias("v"))), "edges")
    size, turn, before = sign(now), 0, None
    if size[0] <= few:
        pairs = now.toArrow()
        ids, at = np.unique(np.concatenate([pairs[c].to_numpy() for c in "uv"]), return_inverse=True)
        low = least_joined(len(ids), *np.split(at, 2))
        discard(now)
        return edges.sparkSession.createDataFrame(pa.table({"id": ids, "component": ids[low]}), "id long, component long")
    while size != before:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        # larger neighbours go to the smallest known vertex
        near = with_least(both, "u", "v", 2 * size[0])
        hung = staged(tidy(near.where("v > u").select(F.col("v").alias("u"), F.least("u", "m").alias("v"))), f"hung{turn}")
        # smaller neighbours, and the vertex itself, too
        drawn = with_least(hung, "u", "v", 2 * size[0]).select(F.col("v").alias("u"), F.col("m").alias("v"))
        low = hung.groupBy("u").agg(F.min("v").alias("v"))
        after = staged(tidy(drawn.unionByName(low)), f"round{turn}")
        discard(hung)
        discard(now)
        now, before, turn = after, size, turn + 1
        size = sign(now)
    return now.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(
        now.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct())
