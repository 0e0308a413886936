"""What skipping is compared with: manual rewriting, ideal skipping, a full inverted index."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sift.functions.geo import ring_of
from sift.session import SiftSession
from sift.sources.lake import LakeSource


def rewrite_with_bounds(df: DataFrame, wkt: str, x: str = "lng", y: str = "lat") -> DataFrame:
    """The polygon's bounding rectangle as range predicates, which the format's own statistics can use."""
    ring = ring_of(wkt)
    xs, ys = [p[0] for p in ring], [p[1] for p in ring]
    return df.where(F.col(x).between(min(xs), max(xs)) & F.col(y).between(min(ys), max(ys)))


def ideal_objects(source: LakeSource, df: DataFrame, predicate: str) -> DataFrame:
    """(path, n_relevant): the objects that any correct skipping must read."""
    return source.tagged(df.where(predicate)).groupBy("path").agg(F.count("*").alias("n_relevant"))


def inverted_index(source: LakeSource, df: DataFrame, column: str) -> DataFrame:
    """(value, postings): for every value its objects and row positions; as large as the data, for comparison only."""
    rows = source.tagged(df, F.col(column).alias("value"), F.expr("_metadata.row_index").alias("row"))
    return rows.groupBy("value", "path").agg(F.array_sort(F.collect_list("row")).alias("rows")).groupBy("value").agg(F.collect_list(F.struct("path", "rows")).alias("postings"))


def without_skipping(session: SiftSession) -> SiftSession:
    """The same lakes, every object read."""
    plain = SiftSession(session.spark, skipping=False)
    plain.lakes = session.lakes
    return plain
