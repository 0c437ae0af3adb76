"""Runs a query beside its SQL twin in DuckDB and tells how their rows differ."""

from __future__ import annotations

import collections
import datetime
import decimal
import math

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def duck(sf_dir: str) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return con


def plain(x):
    if isinstance(x, float):
        return None if math.isnan(x) else round(x, 9) + 0.0
    if isinstance(x, decimal.Decimal):
        return float(x)
    if isinstance(x, datetime.datetime):
        return x.replace(tzinfo=None).isoformat()
    return x


def rows(names, data) -> collections.Counter:
    order = sorted(range(len(names)), key=lambda i: names[i])
    return collections.Counter(tuple(plain(r[i]) for i in order) for r in data)


def differences(df, con, sql: str) -> str:
    """Empty if both sides have the same columns and rows."""
    other = con.sql(sql)
    if sorted(df.columns) != sorted(other.columns):
        return f"columns {sorted(df.columns)} and {sorted(other.columns)}"
    kinds = {k: {"bigint": "BIGINT", "int": "INTEGER", "double": "DOUBLE", "string": "VARCHAR", "boolean": "BOOLEAN"}.get(v) for k, v in df.dtypes}
    odd = [(k, kinds[k], str(t)) for k, t in zip(other.columns, other.types, strict=True) if kinds[k] and str(t) != kinds[k]]
    a, b = rows(df.columns, [tuple(r) for r in df.collect()]), rows(other.columns, other.fetchall())
    only_a, only_b = a - b, b - a
    if only_a or only_b:
        return f"{sum(a.values())} and {sum(b.values())} rows; {sum(only_a.values())} and {sum(only_b.values())} differ: {list(only_a)[:2]} {list(only_b)[:2]}"
    return f"types differ: {odd}" if odd else ""
