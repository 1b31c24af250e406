"""Compare a Spark result with a DuckDB query on the same tables, rows in any order."""

from __future__ import annotations

import os
from pathlib import Path

import duckdb


def connect(sf_dir: str) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    for f in Path(sf_dir).glob("*.parquet"):
        con.execute(f"CREATE VIEW {f.stem} AS SELECT * FROM '{f}{'/*.parquet' if os.path.isdir(f) else ''}'")
    return con


def plain(v):
    if v is None or v != v:
        return None
    return float(v) if isinstance(v, float) else int(v) if hasattr(v, "__index__") and not isinstance(v, bool) else v


def rows(names: list[str], data: list[tuple]) -> list[tuple]:
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted((tuple(plain(r[i]) for i in order) for r in data), key=repr)


def assert_same(df, con: duckdb.DuckDBPyConnection, sql: str) -> None:
    got, want = df.collect(), con.execute(sql)
    names = [c[0] for c in want.description]
    assert sorted(df.columns) == sorted(names)
    assert rows(df.columns, got) == rows(names, want.fetchall())
