"""Merge trees, sorts and running states over streams."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from finegrain.functions.keys import KeySpec
from finegrain.operators.sorter import SortConfig, recursive_sort

EVENTS = T.StructType(
    [
        T.StructField("event_id", T.LongType()),
        T.StructField("ts", T.TimestampType()),
        T.StructField("user_id", T.LongType()),
        T.StructField("event_type", T.StringType()),
        T.StructField("value", T.DoubleType()),
        T.StructField("props", T.StringType()),
    ]
)


def read_events(spark: SparkSession, folder: str, files_per_batch: int = 1) -> DataFrame:
    """A stream of the event files of a folder."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def windowed_min(events: DataFrame, length: str, slide: str | None = None, watermark: str | None = "1 hour") -> DataFrame:
    """Least value of each window of ``ts``; later than the watermark is dropped. Works on streams and tables.

    Workers' partials and their merge are one aggregate: Spark combines partials before they shuffle.
    """
    timed = events.withWatermark("ts", watermark) if watermark else events
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    return timed.groupBy(window.alias("w")).agg(F.min("value").alias("least"), F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "least", "n")


def session_min(events: DataFrame, gap: str, watermark: str | None = "1 hour") -> DataFrame:
    """Least value of each user's sessions."""
    timed = events.withWatermark("ts", watermark) if watermark else events
    return timed.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.min("value").alias("least"), F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "least", "n")


def deduplicated(events: DataFrame, key: str = "event_id", watermark: str = "1 hour") -> DataFrame:
    """First of each key within the watermark."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark([key])


def joined_static(events: DataFrame, table: DataFrame, key: str, how: str = "left") -> DataFrame:
    """Stream rows with a table's columns."""
    return events.join(table, key, how)


def running_min(events: DataFrame, key: str = "user_id", value: str = "value") -> DataFrame:
    """Each key's least value so far, one row for each key and batch."""

    def step(k: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        least, n = state.get if state.exists else (float("inf"), 0)
        for frame in frames:
            least, n = min(least, float(frame[value].min())), n + len(frame)
        state.update((least, n))
        yield pd.DataFrame({key: [k[0]], "least": [least], "n": [n]})

    return events.groupBy(key).applyInPandasWithState(step, f"{key} long, least double, n long", "least double, n long", "update", GroupStateTimeout.NoTimeout)


def sorted_batches(events: DataFrame, key: KeySpec, cfg: SortConfig, sink: Callable[[DataFrame, int], None], checkpoint: str):
    """Sort every micro-batch and hand it to ``sink(ranked, batch)``; a batch that runs again gives the same ranks."""

    def each(batch: DataFrame, number: int) -> None:
        sink(recursive_sort(batch, key, cfg).df, number)

    return events.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint)


def drained(df: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there into Parquet files beside its checkpoint and read them back: every batch its own folder, which
    a batch that runs again overwrites; in ``complete`` mode the last batch alone."""
    spark, out, seen = df.sparkSession, f"{checkpoint}-{name}", []

    def each(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/{number}")
        seen.append(number)

    df.writeStream.foreachBatch(each).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    paths = [f"{out}/{n}" for n in (seen[-1:] if mode == "complete" else dict.fromkeys(seen))]
    return spark.read.schema(df.schema).parquet(*paths) if paths else spark.createDataFrame([], df.schema)
