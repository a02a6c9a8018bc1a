"""Runs queries in Spark and their oracle text in DuckDB over the same tables and compares rows."""

from __future__ import annotations

import math
import os
from collections import Counter

import duckdb


def connect(sf_dir: str):
    con = duckdb.connect()
    for f in sorted(os.listdir(sf_dir)):
        name = f.removesuffix(".parquet")
        path = f"{sf_dir}/{f}" + ("/*.parquet" if os.path.isdir(f"{sf_dir}/{f}") else "")
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{path}'")
    return con


def plain(value):
    if isinstance(value, float):
        return None if math.isnan(value) else float(f"{value:.9g}")
    if isinstance(value, bool) or value is None or isinstance(value, (int, str)):
        return value
    return str(value)


def differences(spark_df, con, sql: str) -> str:
    """Empty if both have the same columns and rows."""
    names = sorted(spark_df.columns)
    got = Counter(tuple(plain(r[c]) for c in names) for r in spark_df.collect())
    rel = con.execute(sql)
    columns = [d[0] for d in rel.description]
    if sorted(columns) != names:
        return f"columns {names} against {sorted(columns)}"
    order = [columns.index(c) for c in names]
    want = Counter(tuple(plain(r[i]) for i in order) for r in rel.fetchall())
    if got != want:
        return f"{sum(got.values())} rows against {sum(want.values())}; only here {list((got - want).items())[:3]}; only there {list((want - got).items())[:3]}"
    return ""
