"""Runs a query and its SQL twin on the same tables and compares names, types and rows."""

from __future__ import annotations

import math
import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SAME = {"INTEGER": "int", "BIGINT": "bigint", "DOUBLE": "double", "BOOLEAN": "boolean", "VARCHAR": "string", "DATE": "date", "FLOAT": "float", "TIMESTAMP": "timestamp_ntz"}


def duck(sf_dir: str) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        if os.path.exists(path):
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{path if os.path.isfile(path) else path + '/*.parquet'}')")
    return con


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 9) + 0.0
    if isinstance(v, (list, tuple)):
        return tuple(map(plain, v))
    return v


def differences(df, sql: str, con) -> str:
    """Empty if equal."""
    cur = con.execute(sql)
    names = [c[0] for c in cur.description]
    types = {c[0]: str(c[1]) for c in cur.description}
    theirs = cur.fetchall()
    if sorted(names) != sorted(df.columns):
        return f"columns {sorted(df.columns)} against {sorted(names)}"
    kinds = dict(df.dtypes)
    odd = {n: (kinds[n], types[n]) for n in names if SAME.get(types[n], kinds[n]) != kinds[n] or types[n] == "HUGEINT" or types[n].startswith("DECIMAL") and not kinds[n].startswith("decimal")}
    order = sorted(names)
    mine = sorted((tuple(plain(r[n]) for n in order) for r in df.collect()), key=repr)
    at = [names.index(n) for n in order]
    theirs = sorted((tuple(plain(r[k]) for k in at) for r in theirs), key=repr)
    if len(mine) != len(theirs):
        return f"{len(mine)} rows against {len(theirs)}; types {odd}"
    bad = [(a, b) for a, b in zip(mine, theirs, strict=True) if a != b]
    if bad:
        return f"{len(bad)} of {len(mine)} rows differ, first {bad[0]} of {order}; types {odd}"
    return f"types {odd}" if odd else ""
