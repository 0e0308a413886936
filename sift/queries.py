"""Registered queries of the skipping engine and their SQL counterparts.

A case is one SQL text that runs in Spark over pruned lakes and in DuckDB over the same views of the given tables; where
the two differ the counterpart is given apart.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from sift import queries_breadth, queries_core, queries_measures
from sift.cases import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "queries_breadth", "queries_core", "queries_measures"]

Query = Callable[[SparkSession, str], DataFrame]
