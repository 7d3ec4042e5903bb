"""Compare a query with its DuckDB SQL: same columns, same multiset of rows."""

from __future__ import annotations

import math
import os
from collections import Counter

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    con.execute("set timezone = 'UTC'")
    for t in TABLES:
        p = f"{sf_dir}/{t}.parquet"
        con.execute(f"create view {t} as select * from read_parquet('{p + '/*.parquet' if os.path.isdir(p) else p}')")
    return con


def plain(x):
    if isinstance(x, float):
        return None if math.isnan(x) else float(f"{x:.9g}")
    if isinstance(x, list | tuple):
        return tuple(plain(y) for y in x)
    if isinstance(x, dict):
        return tuple((k, plain(v)) for k, v in x.items())
    if hasattr(x, "asDict"):
        return plain(x.asDict())
    return x


def differences(df, sql: str, sf_dir: str) -> str:
    """Empty if they agree."""
    con = connect(sf_dir)
    rel = con.execute(sql)
    names = [c[0] for c in rel.description]
    theirs = Counter(tuple(plain(v) for _, v in sorted(zip(names, row, strict=True))) for row in rel.fetchall())
    ours = Counter(tuple(plain(v) for _, v in sorted(zip(df.columns, tuple(row), strict=True))) for row in df.collect())
    if sorted(names) != sorted(df.columns):
        return f"columns {sorted(df.columns)} against {sorted(names)}"
    a, b = ours - theirs, theirs - ours
    return "" if not a and not b else f"{sum(ours.values())} rows against {sum(theirs.values())}; only Spark {list(a.items())[:3]}; only SQL {list(b.items())[:3]}"
