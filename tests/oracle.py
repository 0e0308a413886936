"""The given tables in DuckDB, and values made comparable."""

import datetime as dt
import decimal
import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def duck(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        p = f"{sf_dir}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{p + '/*.parquet' if os.path.isdir(p) else p}'")
    return con


def plain(x):
    if isinstance(x, decimal.Decimal):
        x = float(x)
    if isinstance(x, float):
        return float(f"{x:.9g}")
    if isinstance(x, dt.datetime):
        return x.isoformat()
    if isinstance(x, list | tuple):
        return tuple(map(plain, x))
    return x
