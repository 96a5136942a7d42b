"""Runs queries beside their SQL in DuckDB and compares whole results."""

from __future__ import annotations

import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def database(sf_dir: str):
    con = duckdb.connect()
    for t in TABLES:
        p = f"{sf_dir}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{p + '/*.parquet' if os.path.isdir(p) else p}')")
    return con


def norm(v):
    if isinstance(v, float):
        return 0.0 if v == 0 else round(v, 5)
    if hasattr(v, "as_tuple"):
        return round(float(v), 5)
    return v


def differ(con, df, sql: str) -> str:
    """Empty if both results are equal, whatever the order of rows."""
    cur = con.execute(sql)
    want_cols = [d[0] for d in cur.description]
    want = cur.fetchall()
    if sorted(want_cols) != sorted(df.columns):
        return f"columns {sorted(df.columns)} and {sorted(want_cols)}"
    cols = sorted(want_cols)
    at = [want_cols.index(c) for c in cols]
    a = sorted((tuple(norm(r[c]) for c in cols) for r in df.collect()), key=repr)
    b = sorted((tuple(norm(r[i]) for i in at) for r in want), key=repr)
    if a == b:
        return ""
    bad = [(x, y) for x, y in zip(a, b) if x != y][:2]
    return f"{len(a)} and {len(b)} rows; {bad}"
