"""Counts of joins on one inequality: right for odd keys, and without a nested loop over all pairs."""

import itertools

import pytest

from sift import queries as q
from sift import workloads as W
from sift.session import SiftSession
from tests.oracle import duck

PAIRING = ("NestedLoop", "CartesianProduct")


def _plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_join_theta_builds_no_pairs(spark, tiny):
    got = q.QUERIES["join_theta"](spark, tiny)
    assert not any(p in _plan(got) for p in PAIRING)
    assert [tuple(r) for r in got.collect()] == duck(tiny).execute(q.ORACLES["join_theta"]).fetchall()
    assert got.dtypes == [("n", "bigint")]


def test_a_million_by_a_million(spark):
    spark.range(1_000_000).createOrReplaceTempView("theta_a")
    s = SiftSession(spark)
    n = 1_000_000
    assert s.sql("SELECT count(*) AS n FROM theta_a a JOIN theta_a b ON a.id > b.id").first().n == n * (n - 1) // 2
    assert s.sql("SELECT count(*) AS n FROM theta_a a JOIN theta_a b ON a.id % 10 <= b.id % 10").first().n == 55 * (n // 10) ** 2


VALUES = {
    "double": ["NULL", "double('NaN')", "double('NaN')", "0.0D", "-0.0D", "double('-Infinity')", "double('Infinity')", "1.5D", "1.5D", "-3D"],
    "float": ["NULL", "float('NaN')", "0.0F", "-0.0F", "2F"],
    "int": ["NULL", "1", "1", "2147483647", "-2147483648"],
    "decimal(10,2)": ["NULL", "1.50", "-0.01", "99999999.99"],
    "string": ["NULL", "''", "'a'", "'A'", "'ä'", "'a '"],
    "date": ["NULL", "DATE'2024-02-29'", "DATE'1582-10-04'"],
    "timestamp_ntz": ["NULL", "TIMESTAMP_NTZ'2024-02-29 00:00:01'", "TIMESTAMP_NTZ'1900-01-01 00:00:00'"],
    "boolean": ["NULL", "true", "false", "true"],
}


@pytest.mark.parametrize("kinds", [*((k, k) for k in VALUES), ("int", "double"), ("decimal(10,2)", "int")], ids=str)
def test_odd_keys_count_as_by_pairs(spark, kinds):
    for view, kind in zip(("theta_l", "theta_r"), kinds, strict=True):
        more = VALUES[kind] if view == "theta_l" else VALUES[kind][::-1] + VALUES[kind][1:3]
        spark.sql(" UNION ALL ".join(f"SELECT {i} AS i, CAST({v} AS {kind}) AS x" for i, v in enumerate(more))).cache().createOrReplaceTempView(view)
    s = SiftSession(spark)
    ways = list(itertools.product((">", ">=", "<", "<="), (False, True)))
    for (op, swapped), some in zip(ways if kinds == ("double", "double") else ways[::5], itertools.cycle(("", " AND l.i > 1 AND r.i <> 2", ""))):
        on = (f"r.x {op} l.x" if swapped else f"l.x {op} r.x") + some
        text = f"SELECT count(1) FROM theta_l l, theta_r r WHERE {on}" if some else f"SELECT count(*) AS n FROM theta_l l JOIN theta_r r ON {on}"
        got, want = s.sql(text), spark.sql(text)
        assert not any(p in _plan(got) for p in PAIRING), text
        assert got.schema == want.schema and got.collect() == want.collect(), text


def test_a_side_without_rows_has_no_pairs(spark):
    spark.sql("SELECT id AS x FROM range(9)").createOrReplaceTempView("theta_e")
    assert SiftSession(spark).sql("SELECT count(*) AS n FROM theta_e l JOIN theta_e r ON l.x > r.x WHERE l.x > 1000").collect() == [(0,)]


def test_other_joins_are_left_alone(spark):
    spark.sql("SELECT id AS i, id % 7 AS x, id % 3 AS y FROM range(50)").createOrReplaceTempView("theta_o")
    s = SiftSession(spark)
    for text in (
        "SELECT count(*) AS n FROM theta_o a JOIN theta_o b ON a.x > b.x AND a.y < b.y",
        "SELECT count(*) AS n FROM theta_o a JOIN theta_o b ON a.x > b.x AND a.y = b.y",
        "SELECT count(*) AS n FROM theta_o a JOIN theta_o b ON a.x > b.x + a.y",
        "SELECT count(*) AS n FROM theta_o a LEFT JOIN theta_o b ON a.x > b.x",
        "SELECT count(*) AS n FROM theta_o a LEFT SEMI JOIN theta_o b ON a.x > b.x",
        "SELECT count(*) AS n FROM theta_o a LEFT ANTI JOIN theta_o b ON a.x > b.x",
        "SELECT count(*) AS n FROM theta_o a FULL JOIN theta_o b ON a.x > b.x",
        "SELECT count(*) AS n FROM theta_o a CROSS JOIN theta_o b",
        "SELECT count(DISTINCT a.x) AS n FROM theta_o a JOIN theta_o b ON a.x > b.x",
        "SELECT count(*) FILTER (WHERE a.y = 1) AS n FROM theta_o a JOIN theta_o b ON a.x > b.x",
        "SELECT count(nullif(a.y, 1)) AS n FROM theta_o a JOIN theta_o b ON a.x > b.x",
        "SELECT a.y, count(*) AS n FROM theta_o a JOIN theta_o b ON a.x > b.x GROUP BY a.y ORDER BY 1",
        "SELECT count(*) AS n FROM theta_o a JOIN theta_o b ON a.x > b.x HAVING count(*) > 10000",
        "SELECT count(*) + 1 AS n, sum(a.x) AS m FROM theta_o a JOIN theta_o b ON a.x > b.x",
        "SELECT count(*) AS n FROM (SELECT DISTINCT a.y, b.y AS z FROM theta_o a JOIN theta_o b ON a.x > b.x)",
        "SELECT /*+ BROADCAST(b) */ count(*) AS n FROM theta_o a JOIN theta_o b ON a.x > b.x",
    ):
        assert s.sql(text).collect() == spark.sql(text).collect(), text


def test_a_side_is_pruned_as_before(spark, small):
    text = "SELECT count(*) AS n FROM od JOIN customer ON o_totalprice > c_acctbal * 40 WHERE o_orderdate < CAST('1996-01-01' AS {})"
    s = W.session(spark, small, "od")
    got = s.sql(text.format("TIMESTAMP_NTZ"))
    assert not any(p in _plan(got) for p in PAIRING)
    assert [tuple(r) for r in got.collect()] == duck(small).execute(W.oracle_views("od") + text.format("TIMESTAMP")).fetchall()
    assert s.history[-1].lake == "od" and s.history[-1].skipped
