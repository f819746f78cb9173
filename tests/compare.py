"""Rows of a Spark query beside those of its SQL in DuckDB."""

from __future__ import annotations

from collections import Counter
from pathlib import Path

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def duck(sf_dir: str, tables: dict | None = None) -> duckdb.DuckDBPyConnection:
    db = duckdb.connect()
    for t in TABLES:
        path = Path(sf_dir, f"{t}.parquet")
        if path.exists():
            db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path}{'/*.parquet' if path.is_dir() else ''}'")
    for name, table in (tables or {}).items():
        db.register(name, table)
    return db


def rows_of(columns: list[str], rows) -> Counter:
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return Counter(tuple(round(r[i], 9) if isinstance(r[i], float) else r[i] for i in order) for r in rows)


def differences(df, sql: str, db) -> tuple[list, list, int]:
    """Column names must agree; the rows that only Spark has, and only DuckDB, and the number of rows."""
    got = db.execute(sql)
    names = [d[0] for d in got.description]
    assert sorted(names) == sorted(df.columns), (sorted(names), sorted(df.columns))
    a, b = rows_of(df.columns, df.collect()), rows_of(names, got.fetchall())
    return list((a - b).items())[:5], list((b - a).items())[:5], sum(b.values())
