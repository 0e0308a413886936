"""Joins that Spark lacks or that profit from summaries: as-of, range by buckets, and pruning by join keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sift.session import SiftSession


def as_of_join(left: DataFrame, right: DataFrame, on: str, at: str, value: list[str]) -> DataFrame:
    """Each left row with the ``value`` columns of the latest right row of the same ``on`` not after its ``at``.

    One exchange: both sides are stacked, sorted by time, and the last right row is carried forward. Several right rows
    of one moment: the greatest counts.
    """
    tagged = left.select("*", F.lit(None).cast(right.select(F.struct(*value)).schema[0].dataType).alias("_r"), F.lit(1).alias("_side"))
    other = right.select(on, at, F.struct(*value).alias("_r"), F.lit(0).alias("_side"))
    w = Window.partitionBy(on).orderBy(at, "_side", "_r").rowsBetween(Window.unboundedPreceding, 0)
    both = tagged.unionByName(other, allowMissingColumns=True).withColumn("_last", F.last("_r", ignorenulls=True).over(w))
    return both.where("_side = 1").select(*left.columns, *(F.col(f"_last.{v}").alias(v) for v in value))


def range_join(points: DataFrame, ranges: DataFrame, at: str, lo: str, hi: str, width: float) -> DataFrame:
    """Points with the ranges [lo, hi] that hold them: an equi-join on buckets of ``width``, then the exact test."""
    bucket = lambda c: F.floor(F.col(c) / width)
    p = points.withColumn("_bucket", bucket(at))
    r = ranges.where(F.col(lo) <= F.col(hi)).withColumn("_bucket", F.explode(F.sequence(bucket(lo), bucket(hi))))
    return p.join(r, "_bucket").where((F.col(at) >= F.col(lo)) & (F.col(at) <= F.col(hi))).drop("_bucket")


def join_prune(session: SiftSession, lake: str, fact_key: str, dim: DataFrame, dim_key: str, max_keys: int = 10_000) -> DataFrame:
    """The lake joined with a filtered dimension, objects pruned by the dimension's keys.

    Up to ``max_keys`` distinct keys become an IN list on the lake, more of them a range; either only skips, the join decides.
    """
    keys = dim.select(dim_key).where(F.col(dim_key).isNotNull()).distinct()
    some = [r[0] for r in keys.limit(max_keys + 1).collect()]
    if len(some) <= max_keys:
        cond = F.col(fact_key).isin(some)
    else:
        lo, hi = keys.agg(F.min(dim_key), F.max(dim_key)).first()
        cond = F.col(fact_key).between(lo, hi)
    return session.frame(lake, lambda df: df.where(cond)).join(dim, F.col(fact_key) == F.col(dim_key))
