"""Keep tests: boolean functions over objects' summaries. FALSE means that no row of the object can qualify.

Every test is written as SQL over the summary columns. A summary that is missing (not built, other key, older version)
always keeps its object.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


class KeepTest:
    def sql(self) -> str:
        raise NotImplementedError

    def needs(self) -> set[str]:
        """Summary columns that the test reads."""
        return set()

    def column(self) -> Column:
        return F.expr(self.sql())


@dataclass(frozen=True)
class AlwaysKeep(KeepTest):
    def sql(self) -> str:
        return "true"


@dataclass(frozen=True)
class NeverKeep(KeepTest):
    def sql(self) -> str:
        return "false"


@dataclass(frozen=True)
class SummaryTest(KeepTest):
    """A condition on one summary; ``wants_rows``: it needs a non-null value, so objects without any are skipped."""

    index: str
    condition: str
    wants_rows: bool = True

    def sql(self) -> str:
        empty = f" WHEN `{self.index}`.n_nonnull = 0 THEN false" if self.wants_rows else ""
        return f"(CASE WHEN `{self.index}` IS NULL THEN true{empty} ELSE coalesce({self.condition.replace('{s}', f'`{self.index}`')}, true) END)"

    def needs(self) -> set[str]:
        return {self.index}


@dataclass(frozen=True)
class AndTest(KeepTest):
    parts: tuple[KeepTest, ...]

    def sql(self) -> str:
        return "(" + " AND ".join(p.sql() for p in self.parts) + ")"

    def needs(self) -> set[str]:
        return set().union(*(p.needs() for p in self.parts))


@dataclass(frozen=True)
class OrTest(KeepTest):
    parts: tuple[KeepTest, ...]

    def sql(self) -> str:
        return "(" + " OR ".join(p.sql() for p in self.parts) + ")"

    def needs(self) -> set[str]:
        return set().union(*(p.needs() for p in self.parts))


def all_of(parts: list[KeepTest]) -> KeepTest:
    """Conjunction, simplified; equal tests once."""
    flat: dict[KeepTest, None] = {}
    for p in parts:
        flat.update(dict.fromkeys(p.parts if isinstance(p, AndTest) else (p,)))
    flat.pop(AlwaysKeep(), None)
    if NeverKeep() in flat:
        return NeverKeep()
    return AlwaysKeep() if not flat else next(iter(flat)) if len(flat) == 1 else AndTest(tuple(flat))


def any_of(parts: list[KeepTest]) -> KeepTest:
    """Disjunction, simplified; equal tests once."""
    flat: dict[KeepTest, None] = {}
    for p in parts:
        flat.update(dict.fromkeys(p.parts if isinstance(p, OrTest) else (p,)))
    flat.pop(NeverKeep(), None)
    if AlwaysKeep() in flat:
        return AlwaysKeep()
    return NeverKeep() if not flat else next(iter(flat)) if len(flat) == 1 else OrTest(tuple(flat))
