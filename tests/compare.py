"""Compares a Spark frame with DuckDB's rows: columns by name, rows in any order."""

from __future__ import annotations

import decimal
import math
import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations"


def connect(sf_dir: str):
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES.split():
        path = f"{sf_dir}/{t}.parquet"
        if os.path.isdir(path):
            path += "/*.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{path}')")
    return con


def cell(x):
    if x is None or (isinstance(x, float) and math.isnan(x)):
        return "NULL"
    if isinstance(x, bool):
        return str(x)
    if isinstance(x, decimal.Decimal):
        x = float(x)
    if isinstance(x, float):
        return repr(int(x)) if x == int(x) and abs(x) < 1e15 else f"{x:.9g}"
    if isinstance(x, (list, tuple)):
        return "[" + ",".join(map(cell, x)) + "]"
    if isinstance(x, dict):
        return "{" + ",".join(f"{k}:{cell(v)}" for k, v in x.items()) + "}"
    if hasattr(x, "asDict"):
        return cell(x.asDict())
    return str(x)


def both(frame, con, sql: str):
    names = sorted(frame.columns)
    mine = sorted(tuple(cell(v) for v in r) for r in frame.select(*[f"`{n}`" for n in names]).collect())
    cursor = con.execute(sql)
    theirs_names = [d[0] for d in cursor.description]
    assert sorted(theirs_names) == names, (names, sorted(theirs_names))
    at = [theirs_names.index(n) for n in names]
    theirs = sorted(tuple(cell(r[i]) for i in at) for r in cursor.fetchall())
    return mine, theirs
