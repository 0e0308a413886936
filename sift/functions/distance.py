"""Metric distances: native expressions to build summaries with, opaque functions to query with."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Metric:
    """A metric: the name of its function in queries, its distance of two values in SQL, and a query value in SQL."""

    function: str
    sql: Callable[[str, str], str]
    literal: Callable[[str], str]


def text_literal(text: str) -> str:
    """A string in SQL."""
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def vector_literal(text: str) -> str:
    """A vector, written as numbers between commas, in SQL."""
    return "array(" + ", ".join(f"{float(x)!r}D" for x in text.split(",")) + ")"


def _summed(each: str) -> Callable[[str, str], str]:
    return lambda a, b: f"aggregate(zip_with({a}, {b}, (x, y) -> {each}), 0D, (s, z) -> s + z)"


_squares = _summed("(cast(x as double) - y) * (cast(x as double) - y)")
METRICS = {
    "euclid": Metric("euclid_distance", lambda a, b: f"sqrt({_squares(a, b)})", vector_literal),
    "manhattan": Metric("manhattan_distance", _summed("abs(cast(x as double) - y)"), vector_literal),
    "levenshtein": Metric("levenshtein", lambda a, b: f"cast(levenshtein({a}, {b}) as double)", text_literal),
}


def add_metric(name: str, function: str, sql: Callable[[str, str], str], literal: Callable[[str], str] = text_literal) -> None:
    """Make a user's metric known. ``sql`` must keep the triangle inequality and agree with ``function`` up to rounding."""
    METRICS[name] = Metric(function, sql, literal)


def _distances(v: pd.Series, q: pd.Series, norm) -> pd.Series:
    """``norm`` of the differences, for each query the rows it is asked of; null where either is null or lengths differ."""
    out = pd.Series(np.nan, index=v.index, dtype=float)
    have = v.notna() & q.notna()
    for text, at in q[have].groupby(q[have]).groups.items():
        to = np.array([float(x) for x in text.split(",")])
        rows = v.loc[at]
        rows = rows[rows.map(len) == len(to)]
        if len(rows):
            out.loc[rows.index] = norm(np.stack(rows.to_numpy()).astype(np.float64) - to)
    return out


def register(spark: SparkSession) -> None:
    """euclid_distance(vector, text) and manhattan_distance(vector, text): vectorised Python functions, opaque to the optimizer."""

    @F.pandas_udf("double")
    def euclid_distance(v: pd.Series, q: pd.Series) -> pd.Series:
        return _distances(v, q, lambda d: np.sqrt((d * d).sum(axis=1)))

    @F.pandas_udf("double")
    def manhattan_distance(v: pd.Series, q: pd.Series) -> pd.Series:
        return _distances(v, q, lambda d: np.abs(d).sum(axis=1))

    spark.udf.register("euclid_distance", euclid_distance)
    spark.udf.register("manhattan_distance", manhattan_distance)
