"""Comparing a Spark query with its DuckDB SQL on the same Parquet files."""

from __future__ import annotations

import datetime
import decimal
import glob
import math
import os

import duckdb

SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.01")


def connection(sf_dir: str = SF):
    c = duckdb.connect()
    for path in glob.glob(f"{sf_dir}/*.parquet"):
        c.execute(f"create view {os.path.basename(path)[:-8]} as select * from '{path}'")
    return c


def _plain(v):
    if isinstance(v, bool) or v is None:
        return v
    if isinstance(v, (float, decimal.Decimal)):
        v = float(v)
        return None if math.isnan(v) else round(v, 5) + 0.0
    if isinstance(v, int):
        return v
    if isinstance(v, (datetime.datetime, datetime.date)):
        return str(v)
    return v


def rows_of(names: list[str], rows) -> list[tuple]:
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted((tuple(_plain(r[i]) for i in order) for r in rows), key=lambda t: tuple((x is None, str(x)) for x in t))


def differences(spark, query, sql: str, sf_dir: str = SF, tolerance: float = 2e-5) -> str:
    """Empty if both give the same columns and rows."""
    df = query(spark, sf_dir)
    got = rows_of(df.columns, df.collect())
    rel = connection(sf_dir).execute(sql)
    names = [x[0] for x in rel.description]
    want = rows_of(names, rel.fetchall())
    if sorted(df.columns) != sorted(names):
        return f"columns {sorted(df.columns)} and {sorted(names)}"
    if len(got) != len(want):
        return f"{len(got)} and {len(want)} rows; {got[:3]} {want[:3]}"
    bad = [(g, w) for g, w in zip(got, want, strict=True) if g != w and not all(a == b or isinstance(a, float) and isinstance(b, (int, float)) and abs(a - b) <= tolerance * max(1, abs(a)) for a, b in zip(g, w, strict=True))]
    return f"{len(bad)} rows differ: {bad[:3]}" if bad else ""
