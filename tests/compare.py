"""Compares a Spark result with DuckDB SQL over the same Parquet tables, as sorted rows of text."""

from __future__ import annotations

import datetime
import math
from pathlib import Path


def duck(sf_dir: str):
    import duckdb

    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for p in sorted(Path(sf_dir).glob("*.parquet")):
        con.execute(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p if p.is_file() else f'{p}/*.parquet'}'")
    return con


def plain(x) -> str:
    if x is None or (isinstance(x, float) and math.isnan(x)):
        return "null"
    if isinstance(x, bool):
        return str(x)
    if isinstance(x, datetime.datetime):
        return x.replace(tzinfo=None).isoformat()
    if hasattr(x, "as_tuple") or isinstance(x, float):
        return repr(float(x))
    if isinstance(x, int):
        return repr(float(x)) if False else str(x)
    return str(x)


def rows(names: list[str], data) -> list[tuple[str, ...]]:
    order = sorted(range(len(names)), key=names.__getitem__)
    return sorted(tuple(plain(r[k]) for k in order) for r in data)


def differences(df, con, text: str, limit: int = 5) -> str | None:
    """None if both give the same columns and rows."""
    cur = con.execute(text)
    names = [d[0] for d in cur.description]
    want = rows(names, cur.fetchall())
    got = rows(df.columns, df.collect())
    if sorted(names) != sorted(df.columns):
        return f"columns {sorted(df.columns)} / {sorted(names)}"
    number = lambda r: tuple(_num(x) for x in r)
    got, want = sorted(map(number, got)), sorted(map(number, want))
    if got == want:
        return None
    a, b = set(got), set(want)
    return f"{len(got)} / {len(want)} rows; only here {sorted(a - b)[:limit]}, only there {sorted(b - a)[:limit]}"


def _num(x: str) -> str:
    try:
        return repr(round(float(x), 9))
    except ValueError:
        return x
