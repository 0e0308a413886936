"""Planar geospatial functions, and the regions that predicates on points describe."""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from sift.plans.predicate import Call, Lit, Node, Ref

Ring = tuple[tuple[float, float], ...]


def ring_of(wkt: str) -> Ring:
    """The corners of POLYGON((x y, ...)), the closing one left out."""
    m = re.fullmatch(r"\s*POLYGON\s*\(\(([^()]*)\)\)\s*", wkt, re.I)
    if not m:
        raise ValueError(f"not a polygon with one ring: {wkt[:40]}")
    pts = [tuple(map(float, p.split())) for p in m[1].split(",")]
    if any(len(p) != 2 for p in pts):
        raise ValueError("corners have two coordinates")
    return tuple(pts[:-1] if len(pts) > 1 and pts[0] == pts[-1] else pts)


def contains_expr(ring: Ring, x: Column, y: Column) -> Column:
    """Whether the point is inside, by counting crossings: a native expression."""
    crossings = F.lit(0)
    for (ax, ay), (bx, by) in zip(ring, ring[1:] + ring[:1], strict=True):
        if ay != by:
            hit = ((y < ay) != (y < by)) & (x < F.lit(bx - ax) * (y - ay) / F.lit(by - ay) + ax)
            crossings = crossings + hit.cast("int")
    return crossings % 2 == 1


def contains_numpy(ring: Ring, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    inside = np.zeros(len(x), bool)
    for (ax, ay), (bx, by) in zip(ring, ring[1:] + ring[:1], strict=True):
        if ay != by:
            inside ^= ((y < ay) != (y < by)) & (x < (bx - ax) * (y - ay) / (by - ay) + ax)
    return inside


def contains_sql(ring: Ring, x: str, y: str) -> str:
    """The same as SQL text that other engines run too."""
    parts = []
    for (ax, ay), (bx, by) in zip(ring, ring[1:] + ring[:1], strict=True):
        if ay != by:
            parts.append(f"CASE WHEN (({y} < {ay!r}) <> ({y} < {by!r})) AND {x} < CAST({bx - ax!r} AS DOUBLE) * ({y} - {ay!r}) / CAST({by - ay!r} AS DOUBLE) + {ax!r} THEN 1 ELSE 0 END")
    return f"(({' + '.join(parts)}) % 2 = 1)"


def is_convex(ring: Ring) -> bool:
    """Whether all turns go one way."""
    turns = set()
    n = len(ring)
    for i in range(n):
        (ax, ay), (bx, by), (cx, cy) = ring[i], ring[(i + 1) % n], ring[(i + 2) % n]
        cross = (bx - ax) * (cy - by) - (by - ay) * (cx - bx)
        if cross:
            turns.add(cross > 0)
    return n >= 3 and len(turns) == 1


@dataclass(frozen=True)
class Region:
    """Where satisfying points can be: inside a rectangle; if ``inverted``, outside a convex polygon or a circle."""

    x0: float
    x1: float
    y0: float
    y1: float
    inverted: bool = False
    ring: Ring = ()
    circle: tuple[float, float, float] | None = None

    def may_meet(self, b: str) -> str:
        """SQL: may the box ``b`` (x0, x1, y0, y1) hold a satisfying point?"""
        if not self.inverted:
            near = f"{b}.x0 <= {self.x1!r}D AND {b}.x1 >= {self.x0!r}D AND {b}.y0 <= {self.y1!r}D AND {b}.y1 >= {self.y0!r}D"
            if self.circle:
                cx, cy, r = self.circle
                # An upper bound of NaN hides the numbers below it: nothing is known on that side.
                dx, dy = (f"greatest({b}.{a}0 - {c!r}D, 0D, nanvl({c!r}D - {b}.{a}1, 0D))" for a, c in (("x", cx), ("y", cy)))
                near += f" AND {dx} * {dx} + {dy} * {dy} <= {r * r * (1 + 1e-9)!r}D"
            return near
        corners = [f"({b}.x{i} - {px!r}D) * {qy - py!r}D - ({b}.y{j} - {py!r}D) * {qx - px!r}D" for i in "01" for j in "01" for (px, py), (qx, qy) in zip(self.ring, self.ring[1:] + self.ring[:1], strict=True)]
        # Strictly on the inner side of every edge, for either direction of the ring: then the whole box is inside.
        return f"(isnan({b}.x1) OR isnan({b}.y1) OR NOT (greatest({', '.join(corners)}) < 0 OR least({', '.join(corners)}) > 0))"


def region_of(node: Node, x: str, y: str) -> Region | None:
    """The region that a leaf on the point (x, y) describes, or None.

    Understood are st_contains(wkt, y, x), also negated for convex polygons, st_distance(y, x, y', x') below a number,
    and st_intersects(wkt, y, x), which for points is containment.
    """
    t = node.term
    if not isinstance(t, Call):
        return None
    refs = [a.path for a in t.args if isinstance(a, Ref)]
    lits = [a for a in t.args if isinstance(a, Lit)]
    if refs != [y, x] or any(v.value is None for v in lits):
        return None
    if node.kind == "call" and t.name in ("st_contains", "st_intersects") and len(lits) == 1:
        try:
            ring = ring_of(lits[0].value)
        except ValueError:
            return None
        if len(ring) < 3:
            return None
        if node.negated:
            return Region(0, 0, 0, 0, True, ring) if is_convex(ring) else None
        xs, ys = [p[0] for p in ring], [p[1] for p in ring]
        return Region(min(xs), max(xs), min(ys), max(ys))
    if node.kind == "cmp" and t.name == "st_distance" and node.op in ("<", "<=", "=") and len(lits) == 2:
        cy, cx, r = (float(v.value) for v in (*lits, node.values[0]))
        pad = abs(r) * 1e-9
        return Region(cx - r - pad, cx + r + pad, cy - r - pad, cy + r + pad, circle=(cx, cy, r)) if r >= 0 else None
    return None


def _cross(p, q, r) -> float:
    return (q[0] - p[0]) * (r[1] - p[1]) - (q[1] - p[1]) * (r[0] - p[0])


def rings_intersect(a: Ring, b: Ring) -> bool:
    """Whether two polygons share a point: edges cross, or one holds a corner of the other."""
    edges = lambda r: zip(r, r[1:] + r[:1], strict=True)
    for p, q in edges(a):
        for r, s in edges(b):
            if _cross(p, q, r) * _cross(p, q, s) <= 0 and _cross(r, s, p) * _cross(r, s, q) <= 0 and max(min(p[0], q[0]), min(r[0], s[0])) <= min(max(p[0], q[0]), max(r[0], s[0])) and max(min(p[1], q[1]), min(r[1], s[1])) <= min(max(p[1], q[1]), max(r[1], s[1])):
                return True
    one = lambda r, p: bool(contains_numpy(r, np.array([p[0]]), np.array([p[1]]))[0])
    return one(a, b[0]) or one(b, a[0])


def _corners(shape: pd.Series) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All corners' x and y in a row, and how many each shape has; null shapes and those with a null corner have none."""
    rings = [[(p["x"], p["y"]) for p in s] if s is not None else [] for s in shape]
    rings = [[] if any(None in p for p in r) else r for r in rings]
    flat = np.array([p for r in rings for p in r], float).reshape(-1, 2)
    return flat[:, 0], flat[:, 1], np.array(list(map(len, rings)), np.int64)


def shapes_contain(shape: pd.Series, lat: pd.Series, lng: pd.Series) -> pd.Series:
    """Whether each shape holds its point, its edges included, all edges side by side; null where shape, corner or coordinate
    is null. Sides are told by products alone: a quotient's rounding would move points that lie near an edge or on it."""
    ax, ay, n = _corners(shape)
    first = np.cumsum(n) - n
    after = np.arange(len(ax)) + 1
    last = (first + n - 1)[n > 0]
    after[last] = first[n > 0]
    bx, by = ax[after], ay[after]
    of = np.repeat(np.arange(len(n)), n)
    x, y = pd.to_numeric(lng).to_numpy(float)[of], pd.to_numeric(lat).to_numpy(float)[of]
    with np.errstate(divide="ignore", invalid="ignore"):
        turn = (bx - ax) * (y - ay) - (x - ax) * (by - ay)
        x0, x1 = np.minimum(ax, bx), np.maximum(ax, bx)
        crossed = ((y < ay) != (y < by)) & ((x < x0) | (x <= x1) & (np.where(by > ay, turn, -turn) > 0))
        on = (turn == 0) & (x0 <= x) & (x <= x1) & (np.minimum(ay, by) <= y) & (y <= np.maximum(ay, by))
    odd = pd.Series((np.bincount(of, crossed, len(n)).astype(int) % 2 == 1) | (np.bincount(of, on, len(n)) > 0), index=shape.index, dtype=object)
    odd[(n == 0) | lat.isna().to_numpy() | lng.isna().to_numpy()] = None
    return odd


def shapes_intersect(wkt: pd.Series, shape: pd.Series) -> pd.Series:
    """Whether each shape meets its polygon; edges are looked at only where the rectangles around both meet."""
    x, y, n = _corners(shape)
    first = np.cumsum(n) - n
    out = [None] * len(n)
    rings = {t: ring_of(t) for t in wkt.dropna().unique()}
    for i, t in enumerate(wkt):
        if n[i] and t in rings:
            ring, at = rings[t], slice(first[i], first[i] + n[i])
            xs, ys = zip(*ring, strict=True)
            apart = x[at].max() < min(xs) or x[at].min() > max(xs) or y[at].max() < min(ys) or y[at].min() > max(ys)
            out[i] = not apart and rings_intersect(ring, tuple(zip(x[at].tolist(), y[at].tolist(), strict=True)))
    return pd.Series(out, index=shape.index, dtype=object)


def register(spark: SparkSession) -> None:
    """st_contains(wkt, lat, lng), st_intersects(wkt, lat, lng), st_distance(lat, lng, lat', lng'), and for columns of shapes
    st_shape_contains(shape, lat, lng), st_shape_intersects(wkt, shape): opaque vectorised functions."""

    @F.pandas_udf("boolean")
    def st_shape_contains(shape: pd.Series, lat: pd.Series, lng: pd.Series) -> pd.Series:
        return shapes_contain(shape, lat, lng)

    @F.pandas_udf("boolean")
    def st_shape_intersects(wkt: pd.Series, shape: pd.Series) -> pd.Series:
        return shapes_intersect(wkt, shape)

    def inside(wkt: pd.Series, lat: pd.Series, lng: pd.Series) -> pd.Series:
        found = pd.Series([None] * len(wkt), index=wkt.index, dtype=object)
        have = wkt.notna() & lat.notna() & lng.notna()  # a point without a coordinate is neither inside nor outside
        for text, at in wkt[have].groupby(wkt[have]).groups.items():
            found.loc[at] = contains_numpy(ring_of(text), lng.loc[at].to_numpy(float), lat.loc[at].to_numpy(float))
        return found

    @F.pandas_udf("boolean")
    def st_contains(wkt: pd.Series, lat: pd.Series, lng: pd.Series) -> pd.Series:
        return inside(wkt, lat, lng)

    @F.pandas_udf("boolean")
    def st_intersects(wkt: pd.Series, lat: pd.Series, lng: pd.Series) -> pd.Series:
        return inside(wkt, lat, lng)

    @F.pandas_udf("double")
    def st_distance(lat: pd.Series, lng: pd.Series, lat0: pd.Series, lng0: pd.Series) -> pd.Series:
        dx, dy = lng - lng0, lat - lat0
        return (dx * dx + dy * dy) ** 0.5

    for f in (st_contains, st_intersects, st_distance):
        spark.udf.register(f.__name__, f)
    spark.udf.register("st_shape_contains", st_shape_contains)
    spark.udf.register("st_shape_intersects", st_shape_intersects)
