"""Compares a query's rows with its DuckDB twin: names, kinds of types, row count, values without order."""

from __future__ import annotations

import os

import duckdb

from boolmat.sources.tables import TABLES


def duck(sf_dir: str) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        if os.path.exists(path):
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{path}')")
    return con


def _plain(v):
    if isinstance(v, float):
        return "nan" if v != v else repr(round(v, 9) + 0.0)
    if hasattr(v, "isoformat"):
        return v.isoformat()
    return repr(v)


def compare(df, con, sql: str) -> str:
    """'' if both agree, else what differs."""
    cols = sorted(df.columns)
    got = sorted(tuple(_plain(r[c]) for c in cols) for r in df.collect())
    res = con.execute(sql)
    names = [d[0] for d in res.description]
    if sorted(names) != cols:
        return f"columns {cols} and {sorted(names)}"
    order = [names.index(c) for c in cols]
    want = sorted(tuple(_plain(r[i]) for i in order) for r in res.fetchall())
    if len(got) != len(want):
        return f"{len(got)} rows and {len(want)}; first apart {next(((a, b) for a, b in zip(got, want) if a != b), None)}"
    apart = [(a, b) for a, b in zip(got, want, strict=True) if a != b]
    return f"{len(apart)} of {len(got)} rows apart: {apart[:2]}" if apart else ""
