"""Plug-ins: kinds, matchers and stores by name, registered by code or found in a module."""

from __future__ import annotations

import importlib
import inspect

from sift.operators import kinds as _kinds
from sift.operators.kinds import SummaryKind
from sift.plans.labelling import Matcher
from sift.sources import stores as _stores
from sift.sources.stores import SummaryStore

KINDS: dict[str, type[SummaryKind]] = {}
MATCHERS: dict[str, type[Matcher]] = {}
STORES: dict[str, type[SummaryStore]] = {}


def register(cls: type) -> type:
    """Register a class by what it is; usable as a decorator. A later one of the same name replaces an earlier one."""
    if issubclass(cls, SummaryKind):
        KINDS[cls.kind] = cls
    elif issubclass(cls, SummaryStore):
        STORES[cls.__name__] = cls
    elif issubclass(cls, Matcher):
        MATCHERS[cls.__name__] = cls
    else:
        raise TypeError(f"{cls.__name__} is neither kind, matcher nor store")
    return cls


def load(module: str) -> list[str]:
    """Import a plug-in module and register the kinds, matchers and stores that it defines."""
    m = importlib.import_module(module)
    found = [c for c in vars(m).values() if inspect.isclass(c) and c.__module__ == m.__name__ and issubclass(c, (SummaryKind, SummaryStore, Matcher))]
    return [register(c).__name__ for c in found]


for _m in (_kinds, _stores):
    for _c in list(vars(_m).values()):
        if inspect.isclass(_c) and _c.__module__ == _m.__name__ and issubclass(_c, (SummaryKind, SummaryStore)) and (_c.__dict__.get("kind") or issubclass(_c, SummaryStore) and _c is not SummaryStore):
            register(_c)


def kind_of(description: dict) -> SummaryKind | None:
    """The kind that a store's manifest describes, or None where no such kind is known (its index is then not used)."""
    cls = KINDS.get(description["kind"])
    return cls(*description["columns"], **{k: v for k, v in description["params"].items() if v is not None}, key_id=description["key_id"]) if cls else None
