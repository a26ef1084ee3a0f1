"""Runs registered queries beside their SQL in DuckDB and compares rows."""

from __future__ import annotations

import os
from pathlib import Path

import duckdb

DATA = os.environ.get("ORDSUM_DATA", "/root/testdata/sf0.001")


def views(d: str = DATA) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    con.execute("set timezone = 'UTC'")
    for p in Path(d).glob("*.parquet"):
        con.execute(f"create view {p.stem} as select * from read_parquet('{p}{'/*.parquet' if p.is_dir() else ''}')")
    return con


def _cell(x):
    if x is None or x != x:
        return ""
    if isinstance(x, bool):
        return str(x)
    try:
        return f"{float(x):.6f}" if not isinstance(x, str) else x
    except (TypeError, ValueError):
        return str(x)


def rows(columns: list[str], data) -> list[tuple]:
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(tuple(_cell(r[i]) for i in order) for r in data)


def compare(spark, name: str, f, sql: str, d: str = DATA, con=None) -> str:
    """'' if equal, else what differs."""
    con = con or views(d)
    df = f(spark, d)
    got = rows(df.columns, [tuple(r) for r in df.collect()])
    rel = con.execute(sql)
    cols = [c[0] for c in rel.description]
    want = rows(cols, rel.fetchall())
    if sorted(cols) != sorted(df.columns):
        return f"columns {sorted(df.columns)} and {sorted(cols)}"
    if got != want:
        diff = [x for x in zip(got, want) if x[0] != x[1]][:2]
        return f"{len(got)} and {len(want)} rows, first differences {diff}"
    return ""
