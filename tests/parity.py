"""Holds registered queries against their DuckDB SQL: row count, columns, values in any order."""

from __future__ import annotations

import math
import os
from decimal import Decimal

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    con.sql("SET TimeZone = 'UTC'")
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return con


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else 0.0 if v == 0 else v
    if isinstance(v, Decimal):
        return float(v)
    if isinstance(v, (list, tuple)):
        return tuple(map(plain, v))
    if hasattr(v, "asDict"):
        return tuple(sorted((k, plain(x)) for k, x in v.asDict().items()))
    if isinstance(v, dict):
        return tuple(sorted((k, plain(x)) for k, x in v.items()))
    if isinstance(v, bytearray):
        return bytes(v)
    if hasattr(v, "tzinfo") and v.tzinfo:
        return v.replace(tzinfo=None)
    return v


def rows_of(columns: list[str], rows) -> list[tuple]:
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted((tuple(plain(r[i]) for i in order) for r in rows), key=lambda r: tuple((x is None, str(type(x)) if x is not None else "", str(x)) for x in r))


def difference(df, con, sql: str) -> str:
    """Empty if both have the same rows; else what differs."""
    got_rows = df.collect()
    cur = con.execute(sql)
    want_cols = [c[0] for c in cur.description]
    want_rows = cur.fetchall()
    if sorted(df.columns) != sorted(want_cols):
        return f"columns {sorted(df.columns)} against {sorted(want_cols)}"
    got, want = rows_of(df.columns, got_rows), rows_of(want_cols, want_rows)
    if len(got) != len(want):
        return f"{len(got)} rows against {len(want)}; e.g. {got[:1]} {want[:1]}"
    for a, b in zip(got, want, strict=True):
        if a != b and str(a) != str(b):
            return f"{a} against {b}"
    return ""
