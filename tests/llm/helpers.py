"""Comparing a query with its SQL in DuckDB on the same tables."""

import datetime as dt

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def duck(sf_dir):
    import os

    con = duckdb.connect()
    for t in TABLES:
        p = f"{sf_dir}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{p + '/*.parquet' if os.path.isdir(p) else p}'")
    return con


def plain(x):
    if isinstance(x, float):
        return float(f"{x:.9g}")
    if isinstance(x, dt.datetime):
        return x.isoformat()
    if isinstance(x, (list, tuple)):
        return tuple(map(plain, x))
    return x


def rows_of(df):
    names = sorted(df.columns)
    return sorted((tuple(plain(r[n]) for n in names) for r in df.collect()), key=str), names


def same_as_sql(df, sql, sf_dir):
    got, names = rows_of(df)
    cur = duck(sf_dir).execute(sql)
    have = [c[0] for c in cur.description]
    assert sorted(have) == names, (sorted(have), names)
    want = sorted((tuple(plain(r[have.index(n)]) for n in names) for r in cur.fetchall()), key=str)
    assert len(got) == len(want), (len(got), len(want))
    assert got == want, next((a, b) for a, b in zip(got, want) if a != b)
    return got
