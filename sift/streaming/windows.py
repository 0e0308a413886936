"""Streams of events: windows, sessions, deduplication, joins and state; each run to its end and read back."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from sift.runtime import scratch_path

#: Event time; streams need a zoned timestamp for their watermark.
AT = "at"


def _timed(events: DataFrame, late: str = "0 seconds") -> DataFrame:
    return events.withColumn(AT, F.col("ts").cast("timestamp")).withWatermark(AT, late)


def _started(df: DataFrame) -> DataFrame:
    return df.withColumn("start", F.col("w.start").cast("timestamp_ntz")).drop("w")


def tumbling(events: DataFrame, width: str) -> DataFrame:
    return _started(_timed(events).groupBy(F.window(AT, width).alias("w"), "event_type").agg(F.count("*").alias("n")))


def sliding(events: DataFrame, width: str, step: str) -> DataFrame:
    return _started(_timed(events).groupBy(F.window(AT, width, step).alias("w")).agg(F.count("*").alias("n")))


def sessions(events: DataFrame, gap: str) -> DataFrame:
    return _started(_timed(events).groupBy("user_id", F.session_window(AT, gap).alias("w")).agg(F.count("*").alias("n")))


def deduplicated(events: DataFrame) -> DataFrame:
    return events.select("user_id", "event_type").dropDuplicates()


def with_static(events: DataFrame, customer: DataFrame) -> DataFrame:
    return events.join(customer, F.col("user_id") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


def bounds(events: DataFrame, width: str) -> DataFrame:
    """Summaries of a stream: least and greatest value by window."""
    return _started(_timed(events).groupBy(F.window(AT, width).alias("w")).agg(F.min("value").alias("lo"), F.max("value").alias("hi")))


def running_top(events: DataFrame) -> DataFrame:
    """Count and greatest value of each user, kept as state between micro-batches."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, top = state.get if state.exists else (0, float("-inf"))
        for b in batches:
            n, top = n + len(b), max(top, float(b["value"].max()))
        state.update((n, top))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "top": [top]})

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, top double", "n long, top double", "update", GroupStateTimeout.NoTimeout)


def late_dropped(spark: SparkSession, first: DataFrame, late: DataFrame, width: str, allowed: str) -> DataFrame:
    """Counts by window where ``late`` arrives after ``first``: what is older than the watermark by then is dropped.

    The two arrive as files, one in each micro-batch; only windows that the watermark has passed are given out.
    """
    path = scratch_path(spark, "late")
    stream_of = lambda: spark.readStream.schema(first.schema).option("maxFilesPerTrigger", 1).parquet(path)
    checkpoint, out = scratch_path(spark, "late-checkpoint"), scratch_path(spark, "late-out")
    for part in (first, late):
        part.coalesce(1).write.mode("append").parquet(path)
        counted = _started(_timed(stream_of(), allowed).groupBy(F.window(AT, width).alias("w")).agg(F.count("*").alias("n")))
        counted.writeStream.format("parquet").option("path", out).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out)


def to_end(spark: SparkSession, stream: DataFrame) -> DataFrame:
    """Everything that has arrived, processed; the result rows as a table. Complete results of each group are kept last."""
    name = f"sift_stream_{abs(hash(scratch_path(spark, 'name')))}"
    mode = "update" if "top" in stream.columns else "append" if set(stream.columns) == {"user_id", "event_type"} else "complete"
    run = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", scratch_path(spark, "stream")).trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.table(name)
