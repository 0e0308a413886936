"""A session over lakes with summaries: queries are planned, tested against the summaries, pruned and run."""

from __future__ import annotations

import re
import time
from collections.abc import Callable
from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sift.functions import distance, geo
from sift.operators.build import bind
from sift.operators.kinds import SummaryKind
from sift.operators.theta import counted
from sift.plans import bridge
from sift.plans.keep import AlwaysKeep, KeepTest, any_of
from sift.plans.labelling import Labelled, Matcher, fold, label
from sift.sources.lake import OBJECT_KEY, LakeSource, among, digest
from sift.sources.stores import SummaryStore

#: Of lakes with more objects the skipped ones come to the driver as digests.
COLLECT = 20_000
KEY = "concat_ws('@', path, cast(mtime as string), cast(size as string))"


@dataclass
class Decision:
    """What was decided for one lake in one query.

    Planning needs the skipped objects only. How many objects and bytes were listed and kept is looked up when it is asked
    for first.
    """

    lake: str
    test: KeepTest
    trees: list[Labelled]
    #: Keys of the skipped objects, or their digests.
    skipped: list[str]
    digests: bool
    #: (path, mtime, size, keep) of what is listed.
    verdicts: Callable[[], DataFrame]
    seconds: float = 0.0

    @cached_property
    def _facts(self) -> tuple[int, int, int, int]:
        kept, size = F.col("keep"), F.col("size")
        zero = F.lit(0).cast("long")
        return tuple(self.verdicts().agg(F.count("*"), F.count_if(kept), F.coalesce(F.sum(size), zero), F.coalesce(F.sum(F.when(kept, size)), zero)).first())

    objects = property(lambda self: self._facts[0])
    n_kept = property(lambda self: self._facts[1])
    bytes = property(lambda self: self._facts[2])
    bytes_kept = property(lambda self: self._facts[3])

    @cached_property
    def kept(self) -> list[str]:
        """Keys of the kept objects."""
        return [r.key for r in self.verdicts().where("keep").select(F.expr(KEY).alias("key")).collect()]

    def explain(self) -> str:
        return f"{self.lake}: keep {self.n_kept} of {self.objects} objects where {self.test.sql()}\n" + "\n".join(t.explain() for t in self.trees)


@dataclass
class Lake:
    source: LakeSource
    store: SummaryStore
    kinds: list[SummaryKind]
    matchers: list[Matcher] = field(default_factory=list)
    roots: frozenset[str] = frozenset()


def usable(lake: Lake) -> list[Matcher]:
    """The lake's matchers, of its kinds those whose summaries were stored under the same columns and parameters."""
    stored = lake.store.indexes()
    return [k for k in lake.kinds if k.index in stored and k.same_as(stored[k.index])] + lake.matchers


class SiftSession:
    """Lakes by name. ``sql`` runs a text in which they are views; ``frame`` runs a function of one lake's DataFrame."""

    def __init__(self, spark: SparkSession, *, skipping: bool = True, cached: bool = False):
        self.spark, self.skipping, self.cached = spark, skipping, cached
        self.lakes: dict[str, Lake] = {}
        self.history: list[Decision] = []
        geo.register(spark)
        distance.register(spark)

    def add(self, name: str, source: LakeSource, store: SummaryStore, kinds: list[SummaryKind], matchers: list[Matcher] = ()) -> None:
        """Register a lake whose summaries of ``kinds`` are in ``store``, with matchers beyond the kinds' own."""
        df = source.read(self.spark)
        found = bridge.relations(df)
        self.lakes[name] = Lake(source, store, bind(kinds, source, self.spark), list(matchers), frozenset(found[0].roots) if found else frozenset())
        df.createOrReplaceTempView(name)

    def register_function(self, name: str, function, matcher: Matcher | None = None, lake: str | None = None) -> None:
        """Register a UDF; what its old body was matched by no longer counts."""
        self.spark.udf.register(name, function)
        for x in self.lakes.values():
            x.matchers = [m for m in x.matchers if getattr(m, "function", None) != name]
        if matcher is not None:
            matcher.function = name
            self.lakes[lake].matchers.append(matcher)

    def _decide(self, name: str, predicates: list) -> Decision:
        """The test for all uses of a lake together, evaluated over its summaries."""
        began = time.time()
        lake = self.lakes[name]
        trees = [label(p, usable(lake)) for p in predicates]
        test = any_of([fold(t) for t in trees])
        held: list[str] = []
        digests = False
        if not isinstance(test, AlwaysKeep):
            denied = lake.store.denied(test, self.cached)
            digests = lake.store.objects() > COLLECT
            held = [r.key for r in denied.select((digest(F.expr(KEY)) if digests else F.expr(KEY)).alias("key")).collect()]
        made = Decision(name, test, trees, held, digests, lambda: lake.store.evaluate(test, lake.source.listing(self.spark), self.cached))
        made.seconds = time.time() - began
        self.history.append(made)
        return made

    def prune(self, df: DataFrame, decision: Decision) -> DataFrame:
        """``df`` of the lake without the skipped objects. A file that is unknown, or changes meanwhile, is read: only files
        that were listed with the same path, time and size, and whose summaries deny the predicate, are left out."""
        return df.where(~among(F.expr(OBJECT_KEY), decision.skipped, decision.digests)) if decision.skipped else df

    def _named(self, uses: list) -> dict[str, list]:
        """Predicates by lake, of those that a plan reads."""
        found: dict[str, list] = {}
        for use in uses:
            for name, x in self.lakes.items():
                if x.roots == set(use.roots):
                    found.setdefault(name, []).append(use.predicate)
        return found

    def decide(self, df: DataFrame) -> dict[str, Decision]:
        """Decisions for the lakes that ``df`` reads."""
        return {name: self._decide(name, p) for name, p in self._named(bridge.relations(df)).items()}

    def sql(self, text: str) -> DataFrame:
        """Plan ``text``, decide, and plan it again over views without the skipped objects; then the views are whole again.

        A count of a join on one inequality is taken from the order of its keys."""
        return counted(self._pruned(text))

    def _pruned(self, text: str) -> DataFrame:
        read: dict[str, DataFrame] = {}

        def list_anew(name: str) -> None:
            read[name] = self.lakes[name].source.read(self.spark)
            read[name].createOrReplaceTempView(name)

        for name in self.lakes:
            if re.search(rf"(?i)(?<!\w){re.escape(name)}(?!\w)", text):
                list_anew(name)
        df = self.spark.sql(text)
        if not self.skipping and len(read) == len(self.lakes):
            return df
        uses = self._named(bridge.relations(df))
        if late := [name for name in uses if name not in read]:  # read through other views
            for name in late:
                list_anew(name)
            df = self.spark.sql(text)
            uses = self._named(bridge.relations(df))
        if not self.skipping:
            return df
        pruned = {name: d for name, d in ((name, self._decide(name, p)) for name, p in uses.items()) if d.skipped}
        if not pruned:
            return df
        try:
            for name, d in pruned.items():
                self.prune(read[name], d).drop("_metadata").createOrReplaceTempView(name)
            return self.spark.sql(text)
        finally:
            for name in pruned:
                read[name].createOrReplaceTempView(name)

    def frame(self, name: str, use: Callable[[DataFrame], DataFrame]) -> DataFrame:
        """``use`` of the lake's DataFrame, pruned by the predicates that ``use`` itself puts on it."""
        source = self.lakes[name].source
        df = use(source.read(self.spark))
        if not self.skipping:
            return df
        made = self.decide(df).get(name)
        return use(self.prune(source.read(self.spark), made)) if made and made.skipped else df

    def history_frame(self) -> DataFrame:
        """One row for each decision so far."""
        rows = [(d.lake, d.test.sql(), d.objects, d.objects - d.n_kept, d.bytes, d.bytes - d.bytes_kept, d.seconds) for d in self.history]
        return self.spark.createDataFrame(rows, "lake string, test string, objects int, skipped int, bytes long, bytes_skipped long, seconds double")

    def explain(self, text: str) -> str:
        """Labels, folded test and outcome for every lake of a query, and indexes hidden for want of a key."""
        found = self.decide(self.spark.sql(text))
        hidden = [f"{n}: no key for {', '.join(x.store.hidden())}" for n, x in self.lakes.items() if x.store.hidden()]
        return "\n".join([d.explain() for d in found.values()] + hidden)
