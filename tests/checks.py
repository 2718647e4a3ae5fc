"""Compare a query's rows with its SQL on DuckDB."""

from __future__ import annotations

import math
import os

import duckdb


def views(folder: str) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    for name in os.listdir(folder):
        con.execute(f"CREATE VIEW {name.split('.')[0]} AS SELECT * FROM '{folder}/{name}'")
    return con


def plain(v):
    if v is None or isinstance(v, float) and math.isnan(v):
        return "none"
    if isinstance(v, bool):
        return str(v)
    if isinstance(v, str):
        return v
    try:
        return repr(int(v)) if v == int(v) else repr(round(float(v), 9))
    except (TypeError, ValueError):
        return str(v)


def same_rows(df, con, sql: str) -> bool:
    columns = sorted(df.columns)
    ours = sorted(tuple(plain(r[c]) for c in columns) for r in df.collect())
    got = con.sql(sql)
    assert sorted(got.columns) == columns
    at = [got.columns.index(c) for c in columns]
    theirs = sorted(tuple(plain(r[i]) for i in at) for r in got.fetchall())
    return ours == theirs
