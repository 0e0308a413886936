"""Layouts: dealing rows to objects. Each writes a data set in which rows of one object share a directory ``obj=...``."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def write_by(df: DataFrame, path: str, obj: Column, fmt: str = "parquet") -> None:
    """One object for each value of ``obj``; rows of one value meet in one task only to be written."""
    tagged = df.withColumn("obj", obj.cast("string"))
    tagged.repartition("obj").write.partitionBy("obj").format(fmt).mode("overwrite").save(path)


def layout_random(df: DataFrame, path: str, n: int) -> None:
    """Objects of unrelated rows: a hash of the whole row deals them out."""
    write_by(df, path, F.pmod(F.xxhash64(*(F.to_json(F.struct(c)) for c in df.columns)), F.lit(n)))


def layout_range(df: DataFrame, path: str, column: str, n: int) -> None:
    """``n`` files by ranges of a column."""
    df.repartitionByRange(n, column).write.mode("overwrite").parquet(path)


def layout_time_key(df: DataFrame, path: str, ts: str, unit: str, key: Column | None = None) -> None:
    """Objects by time unit, and inside it by ``key``."""
    at = F.date_format(F.date_trunc(unit, F.col(ts)), "yyyy-MM-dd-HH")
    write_by(df, path, at if key is None else F.concat_ws("-", at, key.cast("string")))


def kd_leaf(df: DataFrame, columns: list[str], leaves: int, accuracy: int = 1000) -> DataFrame:
    """``df`` with the column leaf, by log2(leaves) rounds of halving at the median of alternating columns.

    A round collects one approximate median for each node, at most ``leaves`` of them.
    """
    out, levels = df.withColumn("leaf", F.lit(0)), leaves.bit_length() - 1
    for level in range(levels):
        c = columns[level % len(columns)]
        cuts = {r.leaf: r.m for r in out.groupBy("leaf").agg(F.percentile_approx(c, 0.5, accuracy).alias("m")).collect()}
        cut = F.element_at(F.create_map(*(x for k, v in cuts.items() for x in (F.lit(k), F.lit(v)))), F.col("leaf")) if cuts else F.lit(None)
        out = out.withColumn("leaf", 2 * F.col("leaf") + F.coalesce((F.col(c) > cut).cast("int"), F.lit(0)))
    return out


def layout_kdtree(df: DataFrame, path: str, columns: list[str], leaves: int, also: Column | None = None) -> None:
    """Objects by the leaves of a KD tree over ``columns``, each split further by ``also``."""
    tree = kd_leaf(df, columns, leaves)
    obj = F.col("leaf").cast("string") if also is None else F.concat_ws("-", F.col("leaf").cast("string"), also.cast("string"))
    write_by(tree, path, obj)
