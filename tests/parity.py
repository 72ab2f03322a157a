"""Spark against DuckDB, rows compared as multisets with columns in name order."""

import math

import duckdb

from lpstream.sources.tables import TABLES


def norm(v):
    if isinstance(v, float):
        return None if math.isnan(v) else repr(round(v, 6) + 0.0)
    if isinstance(v, bool) or v is None:
        return v
    if isinstance(v, (list, tuple)):
        return tuple(norm(x) for x in v)
    if isinstance(v, int):
        return v
    if hasattr(v, "as_tuple"):
        return norm(float(v)) if v != int(v) else int(v)
    return str(v)


def rows_of(names, rows):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted((tuple(norm(r[i]) for i in order) for r in rows), key=repr)


def duck(sf, sql):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    rel = con.sql(sql)
    return list(rel.columns), rel.fetchall()


def compare(spark, sf, f, sql):
    """None if equal, else a short account."""
    df = f(spark, sf)
    have = rows_of(df.columns, [tuple(r) for r in df.collect()])
    names, rows = duck(sf, sql)
    if sorted(names) != sorted(df.columns):
        return f"columns {sorted(df.columns)} != {sorted(names)}"
    want = rows_of(names, rows)
    if have == want:
        return None
    a, b = set(map(repr, have)), set(map(repr, want))
    return f"{len(have)} vs {len(want)} rows; only spark {list(a - b)[:3]}; only sql {list(b - a)[:3]}"
