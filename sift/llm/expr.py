"""Small pieces of column expressions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use`` over ``value``, evaluated once: bound as the one element of an array."""
    return F.element_at(F.transform(F.array(value), use), 1)


def fresh(df: DataFrame, name: str) -> str:
    """``name``, or it with underscores appended until ``df`` has no such column."""
    held = {c.lower() for c in df.columns}
    while name.lower() in held:
        name += "_"
    return name
