"""Sorted runs of micro-batches and their merging; windows over streams."""

from __future__ import annotations

import sys

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from tiersort.functions.keys import KeySpec
from tiersort.operators.layout import SortedLayout
from tiersort.operators.sort import Report, merge_levels
from tiersort.sources.sinks import staged

cloudpickle.register_pickle_by_value(sys.modules[__name__])


def merge_runs(df: DataFrame, key: KeySpec, p: int, run: str = "run", merge: str = "arrow") -> SortedLayout:
    """Runs (column ``run``, from 0) as one layout on p PEs of equal size: exact cuts over all runs, one exchange, local merge.

    Runs are numbered by sorting each by itself once more (files don't say in
    which order they were written) and staged.
    """
    rows = df.withColumn("_ms_pe", F.col(run).cast("int"))
    rows = staged(rows.withColumn("_ms_pos", F.row_number().over(Window.partitionBy("_ms_pe").orderBy(*key.steady(df))).cast("long") - 1), "runs")
    return merge_levels(rows, key, p, [p], merge=merge, report=Report(kept=[rows]))


def stream_runs(stream: DataFrame, key: KeySpec, path: str, checkpoint: str):
    """Starts a query that writes each micro-batch as one sorted run (partition ``run`` = batch number) and ends with the available data."""
    def write(batch: DataFrame, number: int) -> None:
        batch.withColumn("run", F.lit(number)).sortWithinPartitions(*key.order()).write.mode("overwrite").parquet(f"{path}/run={number}")

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def read_runs(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.option("basePath", path).parquet(path)


def windowed_counts(stream: DataFrame, ts: str, width: str, delay: str, by: list[str] | None = None) -> DataFrame:
    """Counts by time window; rows later than ``delay`` behind the newest are dropped."""
    return stream.withWatermark(ts, delay).groupBy(F.window(ts, width), *(by or [])).agg(F.count("*").alias("n"))


def distinct_within(stream: DataFrame, ts: str, columns: list[str], delay: str) -> DataFrame:
    """The first row of each value of ``columns`` among those at most ``delay`` apart; what is older is forgotten."""
    return stream.withWatermark(ts, delay).dropDuplicatesWithinWatermark(columns)


def split_late(stream: DataFrame, ts: str, delay: str, path: str, checkpoint: str):
    """Starts a query that writes rows behind the newest earlier row by more than ``delay`` to ``path``/late, others to ``path``/rows.

    The newest time of each batch stands under ``path``/newest by batch
    number, so a batch that runs again splits as it did.
    """
    def write(batch: DataFrame, number: int) -> None:
        spark, old = batch.sparkSession, None
        if number:
            old = spark.read.parquet(f"{path}/newest").where(F.col("batch") < number).agg(F.max("top")).first()[0]
        late = F.lit(False) if old is None else F.col(ts) < F.lit(old).cast(batch.schema[ts].dataType) - F.expr(f"interval {delay}")
        batch.where(~late).write.mode("overwrite").parquet(f"{path}/rows/batch={number}")
        batch.where(late).write.mode("overwrite").parquet(f"{path}/late/batch={number}")
        batch.agg(F.max(ts).alias("top")).write.mode("overwrite").parquet(f"{path}/newest/batch={number}")

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def in_order(stream: DataFrame, by: str, ts: str, value: str, delay: str) -> DataFrame:
    """Rows (by, ts, value) of each ``by`` in the order of ``ts``, numbered (``place``): held back until ``delay`` has passed, then let go."""
    kinds = {f.name: f.dataType.simpleString() for f in stream.schema}
    out = f"{by} {kinds[by]}, {ts} {kinds[ts]}, {value} {kinds[value]}, place long"

    def step(key: tuple, batches, state):
        held, place = ([], 0) if not state.exists else (list(zip(*state.get[:2])), state.get[2])
        held += [(t.value // 1000, v) for b in batches for t, v in zip(b[ts], b[value])]
        mark = state.getCurrentWatermarkMs() * 1000
        held.sort()
        free = [x for x in held if x[0] <= mark]
        rest = held[len(free):]
        state.update(([t for t, _ in rest], [v for _, v in rest], place + len(free)))
        if rest:
            state.setTimeoutTimestamp(max(rest[0][0] // 1000, mark // 1000) + 1)
        yield pd.DataFrame({by: [key[0]] * len(free), ts: pd.to_datetime([t for t, _ in free], unit="us"), value: [v for _, v in free], "place": range(place, place + len(free))})

    rows = stream.select(by, ts, value).withWatermark(ts, delay)
    return rows.groupBy(by).applyInPandasWithState(step, out, f"times array<long>, kept array<{kinds[value]}>, place long", "append", GroupStateTimeout.EventTimeTimeout)
