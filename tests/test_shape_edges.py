"""Points on and near the edges of shapes."""

import numpy as np
import pandas as pd

from sift.functions.geo import shapes_contain


def test_triangles_hold_the_points_on_their_edges():
    """Corners as the queries make them, against exact arithmetic."""
    given = [(12.06, 21.47), (11.5, 21.75), (12.62, 21.19), (12.0, 22.5), (12.5, 22.25), (13.0, 22.5), (11.0, 22.0), (11.0, 21.99), (13.01, 22.0)]
    lat, lng = (np.array([g[i] + 90 if i == 0 else g[i] + 180 for g in given]).round(2) - (90, 180)[i] for i in (0, 1))
    shape = pd.Series([[{"x": b - 1, "y": a - 1}, {"x": b + 1, "y": a - 1}, {"x": b, "y": a + 1}] for a, b in zip(lat, lng, strict=True)])
    got = shapes_contain(shape, pd.Series([12.0] * len(given)), pd.Series([22.0] * len(given)))
    from fractions import Fraction as Q

    want = [Q(12) >= Q(a) - 1 and Q(12) - (Q(a) - 1) <= 2 * (1 - abs(22 - Q(b))) for a, b in zip(lat.tolist(), lng.tolist(), strict=True)]
    assert got.tolist() == want and True in want and False in want
    square = pd.Series([[{"x": x, "y": y} for x, y in ((0.0, 0.0), (2.0, 0.0), (2.0, 2.0), (0.0, 2.0))]] * 6)
    assert shapes_contain(square, pd.Series([0.0, 2.0, 1.0, 1.0, 2.0, 3.0]), pd.Series([0.0, 2.0, 0.0, 2.0, 3.0, 2.0])).tolist() == [True] * 4 + [False] * 2
