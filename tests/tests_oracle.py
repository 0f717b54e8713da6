"""Compare a query with its SQL: columns, rows and values without order."""

from __future__ import annotations

import math
from pathlib import Path

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str):
    import duckdb

    con = duckdb.connect()
    con.sql("SET TimeZone='UTC'")
    for t in TABLES:
        if Path(f"{sf_dir}/{t}.parquet").exists():
            con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return con


def plain(x):
    import datetime
    import decimal

    if isinstance(x, float):
        return "nan" if math.isnan(x) else float(f"{x:.9g}") + 0.0
    if isinstance(x, decimal.Decimal):
        return float(x)
    if isinstance(x, datetime.datetime):
        return x.replace(tzinfo=None).isoformat()
    if isinstance(x, (list, tuple)):
        return tuple(plain(y) for y in x)
    if isinstance(x, dict):
        return tuple(sorted((str(k), plain(v)) for k, v in x.items()))
    if isinstance(x, (bytes, bytearray)):
        return bytes(x).hex()
    return x


def differs(df, con, sql: str) -> str:
    got = df.collect()
    rel = con.sql(sql)
    names, want = rel.columns, rel.fetchall()
    if sorted(df.columns) != sorted(names):
        return f"columns {df.columns} {names}"
    order = sorted(names)
    key = lambda r: tuple((x is None, type(x).__name__, str(x)) for x in r)
    a = sorted((tuple(plain(r[c]) for c in order) for r in got), key=key)
    b = sorted((tuple(plain(r[names.index(c)]) for c in order) for r in want), key=key)
    if len(a) != len(b):
        return f"rows {len(a)} {len(b)}"
    for x, y in zip(a, b):
        if any(u != v and not (isinstance(u, (int, float)) and isinstance(v, (int, float)) and abs(u - v) <= 1e-9 * max(1, abs(u))) for u, v in zip(x, y)):
            return f"{order}: {str(x)[:300]} {str(y)[:300]}"
    kinds = {"bigint": "BIGINT", "int": "INTEGER", "double": "DOUBLE", "string": "VARCHAR", "boolean": "BOOLEAN"}
    types = dict(zip(names, map(str, rel.types)))
    bad = [(c, t, types[c]) for c, t in df.dtypes if t in kinds and types[c] != kinds[t]]
    return f"types {bad}" if bad else ""
