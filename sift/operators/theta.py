"""Counts of joins on one inequality, from the order of the keys: every pair counts, none is built."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sift.plans import bridge

#: Types whose values are equal, for grouping, just if neither is less.
ORDERED = (T.NumericType, T.BooleanType, T.DateType, T.TimestampType, T.TimestampNTZType)


def count_pairs(above: DataFrame, below: DataFrame, ties: bool) -> DataFrame:
    """In one row, as n, how many pairs of keys, the first columns of the two sides, hold above > below, or above >= below with ``ties``.

    The partners of a key are a prefix of the other side's keys in order, so their number is a running sum. Keys are dealt by
    range: sums run inside each range side by side, and one row of each range tells how many keys all later ranges have
    below them. NULLs have no partner; NaN is the greatest value and equals itself, as in Spark's comparisons.
    """
    one, none = F.lit(1).cast("long"), F.lit(0).cast("long")
    sides = above.toDF("k").select("k", one.alias("a"), none.alias("b")).unionAll(below.toDF("k").select("k", none.alias("a"), one.alias("b")))
    keys = sides.where("k IS NOT NULL").groupBy("k").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    dealt = keys.repartitionByRange("k").withColumn("part", F.spark_partition_id())
    under = F.sum("b").over(Window.partitionBy("part").orderBy("k").rowsBetween(Window.unboundedPreceding, 0 if ties else -1))
    runs = dealt.withColumn("under", F.coalesce(under, none))
    parts = runs.groupBy("part").agg(F.min("k").alias("least"), F.sum(F.col("a") * F.col("under")).alias("n"), F.sum("a").alias("a"), F.sum("b").alias("b"))
    in_order = F.sort_array(F.collect_list(F.struct("least", "n", "a", "b")))
    start = F.struct(none.alias("n"), none.alias("under"))
    whole = F.aggregate(in_order, start, lambda s, p: F.struct((s.n + p.n + p.a * s.under).alias("n"), (s.under + p.b).alias("under")))
    return parts.agg(F.coalesce(whole.getField("n"), none).alias("n"))


def counted(df: DataFrame) -> DataFrame:
    """``df``, by ``count_pairs`` where it is nothing but the count of an inner join on one inequality between two sides.

    What each side reads, filters and computes stays as planned. Joins with hints are left to Spark.
    """
    found = bridge.counted_inequality(df)
    if found is None:
        return df
    (above, a), (below, b), ties = found
    above, below = above.select(a.alias("k")), below.select(b.alias("k"))
    types = above.schema["k"].dataType, below.schema["k"].dataType
    if types[0] != types[1] or not (isinstance(types[0], ORDERED) or types[0] == T.StringType()):
        return df
    named = df.schema[0]
    return count_pairs(above, below, ties).select(F.col("n").alias(named.name, metadata=named.metadata))
