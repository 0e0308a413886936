"""Summaries at ingestion: a stream of arriving files is indexed batch by batch."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from sift.operators.build import bind, summary_rows
from sift.operators.kinds import SummaryKind
from sift.sources.lake import LakeSource
from sift.sources.stores import SummaryStore


def stream_summaries(spark: SparkSession, source: LakeSource, kinds: list[SummaryKind], store: SummaryStore, checkpoint: str) -> StreamingQuery:
    """Index the files that have arrived since the last call, each micro-batch appended to the store.

    A batch that is replayed after a failure appends the same objects again; of an object the newest row counts.
    """
    kinds = bind(kinds, source, spark)

    def add(batch: DataFrame, _: int) -> None:
        if not batch.isEmpty():
            store.write(summary_rows(batch, source, kinds), kinds, mode="append")

    stream = source.stream(spark).select("*", F.col("_metadata"))
    return stream.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
