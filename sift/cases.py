"""The registry of queries."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from sift import workloads

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def portable(sql: str) -> str:
    """The text as DuckDB reads it."""
    return sql.replace("TIMESTAMP_NTZ", "TIMESTAMP")


def lake_sql(key: str, lakes: str, sql: str, oracle: str | None = None) -> None:
    """A query over lakes (names between blanks); the oracle runs the same text, or its own, over the lakes' views."""
    names = lakes.split()
    QUERIES[key] = lambda spark, sf_dir: workloads.session(spark, sf_dir, *names).sql(sql)
    views = workloads.oracle_views(*names)
    text = sql if oracle is None else oracle
    ORACLES[key] = portable(f"{views[:-1]}, {text[5:]}" if views and text.startswith("WITH ") else views + text)


def query(key: str, oracle: str | None = None, lakes: str = ""):
    """Decorator for a query in Python."""

    def add(f):
        QUERIES[key] = f
        if oracle is not None:
            ORACLES[key] = portable(workloads.oracle_views(*lakes.split()) + oracle)
        return f

    return add
