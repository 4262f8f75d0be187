"""Compare a query with its SQL in DuckDB: names, row counts and values, whatever the order."""

from __future__ import annotations

import math
import os
from collections import Counter

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str):
    c = duckdb.connect()
    for t in TABLES:
        if os.path.exists(f"{sf_dir}/{t}.parquet"):
            c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return c


def _plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else float(f"{v:.9g}")
    if isinstance(v, list | tuple):
        return tuple(map(_plain, v))
    return v


def rows(names: list[str], found) -> Counter:
    order = sorted(range(len(names)), key=lambda i: names[i])
    return Counter(tuple(_plain(r[i]) for i in order) for r in found)


def difference(df, con, sql: str) -> str | None:
    out = con.sql(sql)
    if sorted(out.columns) != sorted(df.columns):
        return f"columns {sorted(df.columns)} against {sorted(out.columns)}"
    a, b = rows(df.columns, df.collect()), rows(out.columns, out.fetchall())
    if a != b:
        return f"{sum(a.values())} rows against {sum(b.values())}; only here {list((a - b).items())[:3]}; only there {list((b - a).items())[:3]}"
    return None
