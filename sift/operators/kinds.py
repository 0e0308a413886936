"""Summary kinds: what is kept about each object, how it is computed, and which predicates it can disprove.

A kind is built either by aggregates, which all share one pass over the data, or by a second pass that starts from the
first one's results. Its ``match`` gives sound tests for the nodes of a normalised predicate tree.
"""

from __future__ import annotations

import json
import math
import re
import zlib
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import _parse_datatype_string

from sift.functions import distance, geo
from sift.plans.keep import KeepTest, SummaryTest
from sift.plans.labelling import Matcher
from sift.plans.predicate import Call, Lit, Node, Ref

OBJECT = "path"


class SummaryKind(Matcher):
    """One summary of one or more columns. Registered by ``kind``; further kinds subclass this."""

    kind = ""
    #: Whether summary bytes per object do not grow with the object's values.
    bounded = True

    def __init__(self, *columns: str, **params):
        self.columns, self.params = columns, params
        self.key_id = params.pop("key_id", None)

    @property
    def index(self) -> str:
        """The summary's column in the store; columns whose names differ in signs only have different ones."""
        raw = "__".join([self.kind, *self.columns])
        name = re.sub(r"\W", "_", raw)
        return name if name == raw else f"{name}__{zlib.crc32(raw.encode()):08x}"

    def inputs(self) -> list[Column]:
        """What the aggregates read; for most kinds the columns themselves."""
        return [F.col(c) for c in self.columns]

    def aggregates(self, *inputs: Column) -> dict[str, Column]:
        """Fields, each an aggregate of the inputs; n_nonnull is added to them."""
        return {}

    def finish(self, fields: dict[str, Column]) -> dict[str, Column]:
        """Fields of the summary from the aggregated ones."""
        return fields

    def passes(self) -> int:
        return 1 if type(self).second_pass is SummaryKind.second_pass else 2

    def second_pass(self, rows: DataFrame, first: DataFrame) -> DataFrame:
        """(path, summary struct) where one pass isn't enough; ``rows`` has path, c0, c1, ..., ``first`` path and own aggregates."""
        raise NotImplementedError

    #: The term that stands for an extractor in plans; set when the kind is bound to a source.
    signature = None

    def describe(self) -> dict:
        return {"kind": self.kind, "columns": list(self.columns), "params": self.params, "key_id": self.key_id}

    def same_as(self, described: dict) -> bool:
        """Whether a stored description is that of this very summary, parameters included."""
        return all(json.loads(json.dumps(self.describe()[k])) == described[k] for k in ("kind", "columns", "params"))

    def formula_bytes(self, b: float, v: float) -> float:
        """Upper bound of bytes an object, by value size and distinct values."""
        return math.nan

    def test(self, condition: str, wants_rows: bool = True) -> SummaryTest:
        return SummaryTest(self.index, condition, wants_rows)

    def on_own(self, node: Node) -> bool:
        return isinstance(node.term, Ref) and node.term.path == self.columns[0]


#: Up to so many literals are each written into the test.
FEW = 16


def _q(s: str) -> str:
    return Lit(s, "string").sql()


def any_value(values: tuple[Lit, ...], test: Callable[[str], str]) -> str:
    """SQL whether ``test`` holds for any of ``values``. Of more than a few the test is written once, over an array of them."""
    types = {v.type for v in values}
    if len(values) <= FEW or len(types) > 1:
        return " OR ".join(test(v.sql()) for v in values) or "false"
    if types <= {"byte", "short", "integer", "long"}:
        listed = f"transform(split('{','.join(v.value for v in values)}', ','), t -> CAST(t AS {types.pop()}))"
    else:
        listed = f"array({', '.join(v.sql() for v in values)})"
    return f"exists({listed}, v -> {test('v')})"


def literal_head(node: Node) -> tuple[str, bool] | None:
    """(head, exact) of a text leaf: what every match starts with, and whether a start like it is all that is asked."""
    p = node.values[0].value
    if node.op == "starts":
        return p, True
    if node.op == "like" and "\\" not in p:
        head = re.match(r"[^%_]*", p)[0]
        return (head, p == head + "%") if head else None
    return None


def literal_tail(node: Node) -> tuple[str, bool] | None:
    p = node.values[0].value
    if node.op == "ends":
        return p, True
    if node.op == "like" and "\\" not in p:
        tail = re.search(r"[^%_]*$", p)[0]
        return (tail, p == "%" + tail) if tail else None
    return None


def element_test(node: Node, x: str) -> str | None:
    """SQL of a leaf on one value ``x``, or None."""
    v = node.values[0].sql() if node.values else ""
    no = "NOT " if node.negated else ""
    if node.kind == "cmp":
        return f"{x} {node.op} {v}"
    if node.kind == "in":
        return f"{x} IN ({', '.join(a.sql() for a in node.values)})" if node.values else "false"
    if node.kind == "text":
        return {"starts": f"{no}startswith({x}, {v})", "ends": f"{no}endswith({x}, {v})", "contains": f"{no}contains({x}, {v})", "like": f"{no}({x} LIKE {v})", "rlike": f"{no}rlike({x}, {v})"}[node.op]
    return None


class MinMax(SummaryKind):
    """Least and greatest value of an ordered column."""

    kind = "minmax"

    def aggregates(self, c):
        return {"lo": F.min(c), "hi": F.max(c)}

    def formula_bytes(self, b, v):
        return 2 * b

    def match(self, node: Node) -> Iterator[KeepTest]:
        if node.kind == "null" and self.on_own(node):
            yield self.test("{s}.n_nonnull < n_rows", False) if node.op == "is" else self.test("{s}.n_nonnull > 0")
        if not self.on_own(node):
            return
        vs = [v.sql() for v in node.values]
        if node.kind == "cmp" and node.op in ("=", "<=>"):
            yield self.test(f"{{s}}.lo <= {vs[0]} AND {{s}}.hi >= {vs[0]}")
        elif node.kind == "cmp" and node.op == "!=":
            yield self.test(f"NOT ({{s}}.lo = {vs[0]} AND {{s}}.hi = {vs[0]})")
        elif node.kind == "cmp":
            yield self.test(f"{{s}}.{'lo' if node.op[0] == '<' else 'hi'} {node.op} {vs[0]}")
        elif node.kind == "in":
            yield self.test(any_value(node.values, lambda v: f"({{s}}.lo <= {v} AND {{s}}.hi >= {v})"))
        elif node.kind == "text" and (head := literal_head(node)):
            p, n = _q(head[0]), len(head[0])
            if not node.negated:
                yield self.test(f"left({{s}}.lo, {n}) <= {p} AND left({{s}}.hi, {n}) >= {p}")
            elif head[1]:
                yield self.test(f"NOT (startswith({{s}}.lo, {p}) AND startswith({{s}}.hi, {p}))")


def bounds_on(node: Node, column: str) -> list[tuple[str, Lit]]:
    """Comparisons with ``column`` among the parts of an AND, or the leaf itself."""
    leaves = node.children if node.kind == "and" else (node,)
    return [(n.op, n.values[0]) for n in leaves if n.kind == "cmp" and isinstance(n.term, Ref) and n.term.path == column and n.op in ("<", "<=", ">", ">=", "=", "<=>")]


def _interval(bounds: list[tuple[str, Lit]]) -> tuple[str, str]:
    """SQL conditions that the open gap g begins before, and ends after, the interval; "" where it has no such bound."""
    low = [f"g.lo {'<=' if op == '>' else '<'} {v.sql()}" for op, v in bounds if op in (">", ">=", "=", "<=>")]
    high = [f"g.hi {'>=' if op == '<' else '>'} {v.sql()}" for op, v in bounds if op in ("<", "<=", "=", "<=>")]
    return " OR ".join(low), " OR ".join(high)


class GapList(SummaryKind):
    """Open stretches without values, between the least and the greatest: the ``k`` widest; with a workload of ``ranges``
    [a, b] the ``k`` that hold most of them, which for single ranges is the best choice."""

    kind = "gaps"

    def __init__(self, column: str, k: int = 8, ranges: list | None = None, **params):
        chosen = {} if ranges is None else {"ranges": [list(r) for r in ranges]}
        super().__init__(column, k=k, **chosen, **params)

    @property
    def index(self):
        return super().index + ("__chosen" if "ranges" in self.params else "")

    def aggregates(self, c):
        return {"lo": F.min(c), "hi": F.max(c)}

    def second_pass(self, rows, first):
        along = Window.partitionBy(OBJECT).orderBy("hi")
        gaps = rows.where("c0 IS NOT NULL").select(OBJECT, F.col("c0").alias("hi")).distinct().withColumn("lo", F.lag("hi").over(along)).where("lo IS NOT NULL")
        best = [F.desc("wide"), F.col("lo")]
        gaps = gaps.withColumn("wide", F.col("hi") - F.col("lo"))
        if "ranges" in self.params:
            work = F.array(*(F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a, b in self.params["ranges"])) if self.params["ranges"] else F.expr("array()").cast("array<struct<a:int,b:int>>")
            gaps = gaps.withColumn("hits", F.size(F.filter(work, lambda r: (F.col("lo") < r["a"]) & (r["b"] < F.col("hi"))))).where("hits > 0")
            best = [F.desc("hits"), *best]
        held = gaps.withColumn("n", F.row_number().over(Window.partitionBy(OBJECT).orderBy(*best))).where(F.col("n") <= self.params["k"])
        held = held.groupBy(OBJECT).agg(F.array_sort(F.collect_list(F.struct("lo", "hi"))).alias("gaps"))
        joined = first.join(held, OBJECT, "left")
        none = F.expr("array()").cast(joined.schema["gaps"].dataType)
        return joined.select(OBJECT, F.struct("n_nonnull", "lo", "hi", F.coalesce("gaps", none).alias("gaps")).alias(self.index))

    def formula_bytes(self, b, v):
        return self.params["k"] * b

    def match(self, node: Node) -> Iterator[KeepTest]:
        def outside(low: str, high: str) -> str:
            return f"NOT exists({{s}}.gaps, g -> {' AND '.join(f'({x})' for x in (low, high))})"

        column = self.columns[0]
        bounds = bounds_on(node, column)
        low, high = _interval(bounds)
        if low and high and (node.kind == "and" or node.op in ("=", "<=>")):
            yield self.test(outside(low, high))
        for op, v in bounds:  # a single bound: nothing lies beyond the ends
            if op[0] != "=" and op != "<=>" and node.kind == "cmp":
                yield self.test(f"{{s}}.{'lo' if op[0] == '<' else 'hi'} {op} {v.sql()}")
        if node.kind == "in" and self.on_own(node):
            yield self.test(any_value(node.values, lambda v: "(" + outside(f"g.lo < {v}", f"g.hi > {v}") + ")"))


def _halved(rows: DataFrame, x: str, y: str, times: int) -> DataFrame:
    """``rows`` with a column cell: each object's points (x, y) halved along the longer side until there are ``times`` cells."""
    at = rows.withColumn("cell", F.lit(0))
    for _ in range(int(math.log2(times))):
        w = Window.partitionBy(OBJECT, "cell")
        spread = lambda c: F.max(c).over(w) - F.min(c).over(w)  # noqa: E731, B023
        at = at.withColumn("along", F.when(spread(x) >= spread(y), F.col(x)).otherwise(F.col(y)))
        at = at.withColumn("cell", 2 * F.col("cell") + F.ntile(2).over(w.orderBy("along")) - 1).drop("along")
    return at


def _listed(box: DataFrame, index: str) -> DataFrame:
    """(path, summary struct) from a row for each box (path, x0, x1, y0, y1, n)."""
    return box.groupBy(OBJECT).agg(F.struct(F.sum("n").alias("n_nonnull"), F.array_sort(F.collect_list(F.struct("x0", "x1", "y0", "y1"))).alias("boxes")).alias(index))


class BoxSet(SummaryKind):
    """Bounding boxes of the points (x, y): one, or 2, 4, 8 by halving along the longer side."""

    kind = "boxes"

    def __init__(self, x: str, y: str, boxes: int = 1, **params):
        super().__init__(x, y, boxes=boxes, **params)

    @property
    def index(self):
        return f"{super().index}__{self.params['boxes']}"

    def aggregates(self, x, y):
        return {"x0": F.min(x), "x1": F.max(x), "y0": F.min(y), "y1": F.max(y)} if self.params["boxes"] == 1 else {}

    def finish(self, f):
        return {"boxes": F.array(F.struct(*(f[k].alias(k) for k in ("x0", "x1", "y0", "y1"))))}

    def passes(self):
        return 1 if self.params["boxes"] == 1 else 2

    def second_pass(self, rows, first):
        at = _halved(rows.where("c0 IS NOT NULL AND c1 IS NOT NULL"), "c0", "c1", self.params["boxes"])
        box = at.groupBy(OBJECT, "cell").agg(F.min("c0").alias("x0"), F.max("c0").alias("x1"), F.min("c1").alias("y0"), F.max("c1").alias("y1"), F.count("*").alias("n"))
        return _listed(box, self.index)

    def formula_bytes(self, b, v):
        return 2 * self.params["boxes"] * b * 2

    def match(self, node: Node) -> Iterator[KeepTest]:
        x, y = self.columns
        if node.kind == "and" and bounds_on(node, x) and bounds_on(node, y):
            parts = [f"b.{c}{'0' if op[0] == '<' else '1'} {op} {v.sql()}" for c, col in (("x", x), ("y", y)) for op, v in bounds_on(node, col) if op[0] in "<>" and op != "<=>"]
            if parts:
                yield self.test(f"exists({{s}}.boxes, b -> {' AND '.join(parts)})")
        if (region := geo.region_of(node, x, y)) is not None:
            yield self.test(f"exists({{s}}.boxes, b -> {region.may_meet('b')})")


class GeoMinMax(MinMax):
    """Min/max of one coordinate, used also for geospatial functions on it and its partner."""

    def __init__(self, column: str, other: str, axis: str, **params):
        super().__init__(column, **params)
        self.other, self.axis = other, axis

    def match(self, node):
        yield from super().match(node)
        x, y = (self.columns[0], self.other) if self.axis == "x" else (self.other, self.columns[0])
        region = geo.region_of(node, x, y)
        if region is not None and not region.inverted:
            lo, hi = (region.x0, region.x1) if self.axis == "x" else (region.y0, region.y1)
            yield self.test(f"{{s}}.lo <= {hi!r}D AND {{s}}.hi >= {lo!r}D")


class Bloom(SummaryKind):
    """Bloom filter of a hashable column, sized for each object's distinct values, or for ``expected`` of them."""

    kind = "bloom"

    def __init__(self, column: str, fpp: float = 0.01, expected: int | None = None, **params):
        super().__init__(column, fpp=fpp, expected=expected, **params)

    @property
    def hashes(self) -> int:
        return max(1, round(-math.log2(self.params["fpp"])))

    def bits(self, v: Column) -> Column:
        n = F.lit(self.params["expected"]) if self.params["expected"] else v
        return F.greatest(F.lit(64), F.ceil(F.greatest(n, F.lit(1)) * (-math.log(self.params["fpp"]) / math.log(2) ** 2))).cast("long")

    def listing(self, v: Column) -> Column:
        """Whether the values of an object with ``v`` of them are listed, in place of a filter."""
        return F.lit(False)

    def filled(self, rows: DataFrame) -> DataFrame:
        """(o, v, vs, m, words) of the objects with values: how many, and the values themselves or the filter's size in bits and
        its 64-bit words.

        o is a hash of the path, so that paths don't travel with the values. Objects that should share one share a summary of
        all their values, which skips less and never too much. The distinct values are named twice only, to be counted and to
        be met by their number, so that plans of many kinds stay small; both uses share a scan and an exchange.
        """
        value = F.col("c0") + 0.0 if dict(rows.dtypes)["c0"] in ("double", "float") else F.col("c0")  # -0.0 is 0.0
        values = rows.where("c0 IS NOT NULL").select(F.xxhash64(OBJECT).alias("o"), value.alias("c0")).distinct()
        counted = values.groupBy("o").agg(F.count("*").alias("v"))
        listed = self.listing(F.col("v"))
        sized = values.join(counted.hint("shuffle_hash"), "o").select("o", "v", "c0", self.bits(F.col("v")).alias("m"))
        bits = F.array(*(F.pmod(F.xxhash64("c0", F.lit(i)), F.col("m")) for i in range(self.hashes)))
        at = sized.select("o", "v", F.when(listed, F.col("c0")).alias("c0"), F.explode(F.when(listed, F.array(F.lit(None).cast("long"))).otherwise(bits)).alias("bit"))
        each = at.groupBy("o", "v", "c0", F.expr("bit div 64").alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(bit % 64 as int))")).alias("bits"))
        whole = each.groupBy("o", "v").agg(F.array_sort(F.collect_list("c0")).alias("vs"), F.array_sort(F.collect_list(F.when(F.col("w").isNotNull(), F.struct("w", "bits")))).alias("set"))
        whole = whole.select("o", "v", F.when(listed, F.col("vs")).alias("vs"), F.when(~listed, self.bits(F.col("v"))).alias("m"), "set")
        # Words without bits are put in by what each word follows: looking each place up in a map would make the map anew for
        # every place.
        before = F.expr("concat(array(-1L), slice(set.w, 1, greatest(size(set) - 1, 0)))")
        zeros = lambda n: F.array_repeat(F.lit(0).cast("long"), n.cast("int"))
        words = F.flatten(F.zip_with("set", before, lambda s, b: F.concat(zeros(s["w"] - b - 1), F.array(s["bits"]))))
        return whole.select("o", "v", "vs", "m", F.when(F.col("m").isNotNull(), F.concat(words, zeros(F.expr("(m - 1) div 64 - element_at(set.w, -1)")))).alias("words"))

    #: Fields of the summary.
    fields = ("m", "words")

    def second_pass(self, rows, first):
        joined = first.withColumn("o", F.xxhash64(OBJECT)).join(self.filled(rows), "o", "left")
        return joined.select(OBJECT, F.struct("n_nonnull", F.coalesce("v", F.lit(0).cast("long")).alias("v"), *self.fields).alias(self.index))

    def formula_bytes(self, b, v):
        return -v * math.log(self.params["fpp"]) / math.log(2) ** 2 / 8

    def probe(self, v: Lit) -> str:
        return self._held(v.sql(), v.type)

    def _held(self, v: str, of: str) -> str:
        one = f"{v} + 0.0D" if of in ("double", "float") else v
        bit = lambda i: f"pmod(xxhash64({one}, {i}), {{s}}.m)"
        return "(" + " AND ".join(f"getbit({{s}}.words[cast({bit(i)} div 64 as int)], cast({bit(i)} % 64 as int)) = 1" for i in range(self.hashes)) + ")"

    def probes(self, node: Node) -> str | None:
        """SQL whether the filter may hold one of an equality's values, or None."""
        if not (node.kind == "in" or node.kind == "cmp" and node.op in ("=", "<=>")) or any(v.type != node.term.type for v in node.values):
            return None
        return any_value(node.values, lambda v: self._held(v, node.term.type))

    def match(self, node: Node) -> Iterator[KeepTest]:
        if self.on_own(node) and (t := self.probes(node)) is not None:
            yield self.test(t)


class ValueList(SummaryKind):
    """All distinct values; of an array column, all its elements (``elements=True``)."""

    kind = "list"
    bounded = False

    def __init__(self, column: str, elements: bool = False, **params):
        super().__init__(column, elements=elements, **params)

    def inputs(self):
        return [F.expr(self.columns[0]) if self.params["elements"] else F.col(self.columns[0])]

    def aggregates(self, c):
        return {"vs": F.array_distinct(F.flatten(F.collect_set(c))) if self.params["elements"] else F.collect_set(c)}

    def finish(self, f):
        return {"vs": F.array_sort(f["vs"])}

    def formula_bytes(self, b, v):
        return v * b

    def match(self, node: Node) -> Iterator[KeepTest]:
        if node.kind == "member" and self.params["elements"] and node.term == self.signature:
            yield self.test(f"array_contains({{s}}.vs, {node.values[0].sql()})")
        elif self.on_own(node) and not self.params["elements"]:
            if node.kind == "null":
                yield self.test("{s}.n_nonnull < n_rows", False) if node.op == "is" else self.test("{s}.n_nonnull > 0")
            elif (t := element_test(node, "x")) is not None:
                yield self.test(f"exists({{s}}.vs, x -> {t})")


class PrefixList(SummaryKind):
    """The distinct first ``length`` characters."""

    kind = "prefix"
    bounded = False

    def __init__(self, column: str, length: int = 15, **params):
        super().__init__(column, length=length, **params)

    @property
    def index(self):
        return f"{super().index}__{self.params['length']}"

    def cut(self, x: str) -> str:
        return x[: self.params["length"]]

    def inputs(self):
        return [F.left(F.col(self.columns[0]), F.lit(self.params["length"]))]

    def aggregates(self, c):
        return {"vs": F.collect_set(c)}

    def finish(self, f):
        return {"vs": F.array_sort(f["vs"])}

    def formula_bytes(self, b, v):
        return v * self.params["length"]

    literal, keeps = staticmethod(literal_head), "startswith"

    def match(self, node: Node) -> Iterator[KeepTest]:
        if not self.on_own(node):
            return
        n = self.params["length"]
        if node.kind == "in" or node.kind == "cmp" and node.op in ("=", "<=>"):
            yield self.test(f"arrays_overlap({{s}}.vs, array({', '.join(_q(self.cut(v.value)) for v in node.values)}))" if node.values else "false")
        elif node.kind == "text" and (part := self.literal(node)):
            text, exact = part
            if not node.negated:
                yield self.test(f"exists({{s}}.vs, x -> {self.keeps}(x, {_q(text)}))" if len(text) <= n else f"array_contains({{s}}.vs, {_q(self.cut(text))})")
            elif exact and len(text) <= n:
                yield self.test(f"exists({{s}}.vs, x -> NOT {self.keeps}(x, {_q(text)}))")


class SuffixList(PrefixList):
    """The distinct last ``length`` characters."""

    kind = "suffix"
    literal, keeps = staticmethod(literal_tail), "endswith"

    def cut(self, x):
        return x[-self.params["length"] :]

    def inputs(self):
        return [F.right(F.col(self.columns[0]), F.lit(self.params["length"]))]


class Template(SummaryKind):
    """Distinct values of a piece that ``extractor`` (SQL over the column) takes out of a formatted string."""

    kind = "template"
    bounded = False

    def __init__(self, column: str, extractor: str, name: str = "piece", **params):
        super().__init__(column, extractor=extractor, name=name, **params)

    @property
    def index(self):
        return f"{super().index}__{self.params['name']}"

    def inputs(self):
        return [F.expr(self.params["extractor"])]

    def aggregates(self, c):
        return {"vs": F.collect_set(c)}

    def finish(self, f):
        return {"vs": F.array_sort(f["vs"])}

    def match(self, node: Node) -> Iterator[KeepTest]:
        if node.term is not None and node.term == self.signature and (t := element_test(node, "x")) is not None:
            yield self.test(f"exists({{s}}.vs, x -> {t})")


class MetricRing(SummaryKind):
    """Distances of all values from an origin: a value of the object itself, one given for all objects, or, of vectors, the
    object's mean (``centroid``). The metric is one of ``distance.METRICS``, to which users add their own."""

    kind = "ring"

    def __init__(self, column: str, metric: str = "euclid", origin: str | None = None, centroid: bool = False, **params):
        if centroid and origin is not None:
            raise ValueError("an origin is either given or the centroid")
        super().__init__(column, metric=metric, origin=origin, **({"centroid": True} if centroid else {}), **params)

    @property
    def index(self):
        return f"{super().index}__{self.params['metric']}" + ("__centroid" if "centroid" in self.params else "")

    @property
    def metric(self) -> distance.Metric:
        return distance.METRICS[self.params["metric"]]

    def aggregates(self, c):
        given = self.params["origin"]
        if "centroid" in self.params:
            return {}
        return {"origin": F.min_by(c, F.xxhash64(c)) if given is None else F.first(F.expr(self.metric.literal(given)))}

    def second_pass(self, rows, first):
        if "centroid" in self.params:
            mean = rows.select(OBJECT, F.posexplode("c0").alias("pos", "x")).groupBy(OBJECT, "pos").agg(F.avg("x").alias("x"))
            mean = mean.groupBy(OBJECT).agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "x"))), lambda p: p["x"]).alias("origin"))
            first = first.join(mean, OBJECT, "left")
        at = rows.where("c0 IS NOT NULL").join(first.select(OBJECT, "origin"), OBJECT)
        d = F.expr(self.metric.sql("c0", "origin"))
        ring = at.groupBy(OBJECT).agg(F.min(d).cast("double").alias("dmin"), F.max(d).cast("double").alias("dmax"))
        return first.join(ring, OBJECT, "left").select(OBJECT, F.struct("n_nonnull", "origin", "dmin", "dmax").alias(self.index))

    def match(self, node: Node) -> Iterator[KeepTest]:
        t = node.term
        if node.kind != "cmp" or not isinstance(t, Call) or t.name != self.metric.function or len(t.args) != 2:
            return
        ref = [a for a in t.args if isinstance(a, Ref)]
        lit = [a for a in t.args if isinstance(a, Lit)]
        if len(ref) != 1 or len(lit) != 1 or ref[0].path != self.columns[0] or lit[0].value is None:
            return
        q = self.metric.sql("{s}.origin", self.metric.literal(lit[0].value))
        r = f"cast({node.values[0].sql()} as double)"
        slack = f"1e-9D * (1 + {{s}}.dmax + abs({r}))"
        if node.op in ("<", "<=", "="):
            yield self.test(f"{q} - {r} <= {{s}}.dmax + {slack} AND {q} + {r} >= {{s}}.dmin - {slack}")
        if node.op in (">", ">="):
            yield self.test(f"{q} + {{s}}.dmax >= {r} - {slack}")


class Hybrid(Bloom):
    """A value list where an object has few distinct values, a Bloom filter where it has more than ``threshold``."""

    kind = "hybrid"

    def __init__(self, column: str, threshold: int = 10_000, fpp: float = 0.01, **params):
        super().__init__(column, fpp=fpp, threshold=threshold, **params)

    fields = ("vs", "m", "words")

    def listing(self, v):
        return v <= self.params["threshold"]

    def match(self, node: Node) -> Iterator[KeepTest]:
        if not self.on_own(node) or (t := element_test(node, "x")) is None:
            return
        other = self.probes(node)
        yield self.test(f"CASE WHEN {{s}}.vs IS NOT NULL THEN exists({{s}}.vs, x -> {t}) ELSE ({'true' if other is None else other}) END")


class RangeBits(SummaryKind):
    """A further kind as a plug-in: which of ``buckets`` equal ranges between ``low`` and ``high`` hold values."""

    kind = "rangebits"

    def __init__(self, column: str, low: float, high: float, buckets: int = 64, **params):
        super().__init__(column, low=low, high=high, buckets=buckets, **params)

    def inputs(self):
        p = self.params
        return [F.least(F.greatest(F.floor((F.col(self.columns[0]) - p["low"]) * p["buckets"] / (p["high"] - p["low"])), F.lit(0)), F.lit(p["buckets"] - 1))]

    def aggregates(self, c):
        return {"vs": F.collect_set(c)}

    def _bucket(self, v: Lit) -> int:
        p = self.params
        return min(max(math.floor((float(v.value) - p["low"]) * p["buckets"] / (p["high"] - p["low"])), 0), p["buckets"] - 1)

    def match(self, node: Node) -> Iterator[KeepTest]:
        bounds = bounds_on(node, self.columns[0])
        if bounds and all(v.type in ("double", "integer", "long", "float") for _, v in bounds):
            low = max([self._bucket(v) for op, v in bounds if op[0] != "<" or op == "<=>"], default=0)
            high = min([self._bucket(v) for op, v in bounds if op[0] != ">"], default=self.params["buckets"] - 1)
            yield self.test(f"exists({{s}}.vs, x -> x BETWEEN {low} AND {high})")


class ShapeBoxes(SummaryKind):
    """Rectangles around the shapes of a polygon column (array of x, y structs): one around all, or 2, 4, 8 around as many
    groups, by halving the shapes' centres along the longer side."""

    kind = "shapebox"

    def __init__(self, column: str, boxes: int = 1, **params):
        super().__init__(column, boxes=boxes, **params)

    @property
    def index(self):
        return f"{super().index}__{self.params['boxes']}"

    def inputs(self):
        return [F.expr(f"array_{end}(transform({self.columns[0]}, p -> p.{axis}))") for axis in "xy" for end in ("min", "max")]

    def aggregates(self, x0, x1, y0, y1):
        return {"x0": F.min(x0), "x1": F.max(x1), "y0": F.min(y0), "y1": F.max(y1)} if self.params["boxes"] == 1 else {}

    def finish(self, f):
        return {"boxes": F.array(F.struct(*(f[k].alias(k) for k in ("x0", "x1", "y0", "y1"))))}

    def passes(self):
        return 1 if self.params["boxes"] == 1 else 2

    def second_pass(self, rows, first):
        whole = rows.where("c0 IS NOT NULL AND c2 IS NOT NULL").withColumns({"mx": F.expr("c0 + (c1 - c0) / 2"), "my": F.expr("c2 + (c3 - c2) / 2")})
        at = _halved(whole, "mx", "my", self.params["boxes"])
        box = at.groupBy(OBJECT, "cell").agg(F.min("c0").alias("x0"), F.max("c1").alias("x1"), F.min("c2").alias("y0"), F.max("c3").alias("y1"), F.count("*").alias("n"))
        return _listed(box, self.index)

    def formula_bytes(self, b, v):
        return 4 * self.params["boxes"] * b

    def match(self, node: Node) -> Iterator[KeepTest]:
        t = node.term
        if node.kind != "call" or node.negated or not isinstance(t, Call) or [a.path for a in t.args if isinstance(a, Ref)] != [self.columns[0]]:
            return
        lits = [a.value for a in t.args if isinstance(a, Lit)]
        if t.name == "st_shape_contains" and len(lits) == 2 and None not in lits:
            y, x = map(float, lits)
            yield self.meeting(x, x, y, y)
        elif t.name == "st_shape_intersects" and len(lits) == 1 and lits[0]:
            xs, ys = zip(*geo.ring_of(lits[0]), strict=True)
            yield self.meeting(min(xs), max(xs), min(ys), max(ys))

    def meeting(self, x0: float, x1: float, y0: float, y1: float) -> SummaryTest:
        return self.test(f"exists({{s}}.boxes, b -> b.x0 <= {x1!r}D AND b.x1 >= {x0!r}D AND b.y0 <= {y1!r}D AND b.y1 >= {y0!r}D)")


class ArrowSummaryKind(SummaryKind):
    """Escape hatch: ``collect`` sees one object's rows as Arrow batches and gives the fields of its summary.

    Subclasses set ``fields`` (SQL types, n_nonnull excluded). The columns are exchanged by object, so use it only where
    no aggregate expresses the summary.
    """

    fields = ""

    def collect(self, batches: Iterator) -> dict:
        raise NotImplementedError

    def second_pass(self, rows, first):
        names = [f.split()[0] for f in self.fields.split(",")]
        schema = f"{OBJECT} string, {self.fields}"
        collect, types = self.collect, to_arrow_schema(_parse_datatype_string(schema))

        def run(key: tuple, table: pa.Table) -> pa.Table:
            got = collect(iter(table.to_batches()))
            return pa.Table.from_pylist([{OBJECT: key[0].as_py(), **got}], schema=types)

        held = rows.groupBy(OBJECT).applyInArrow(run, schema)
        return first.join(held, OBJECT, "left").select(OBJECT, F.struct("n_nonnull", *names).alias(self.index))


def default_kinds(schema) -> list[SummaryKind]:
    """The policy of indexing everything at a fixed number of bytes: min/max for ordered columns, sized Bloom filters for strings."""
    out: list[SummaryKind] = []
    for f in schema:
        t = f.dataType.simpleString()
        if t in ("tinyint", "smallint", "int", "bigint", "float", "double", "date", "timestamp", "timestamp_ntz", "string") or t.startswith("decimal"):
            out.append(MinMax(f.name))
        if t == "string":
            out.append(Bloom(f.name, expected=1000))
    return out
