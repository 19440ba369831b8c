"""Compares a query with its oracle SQL the way the driver does: rows and values without order, columns by name."""

from __future__ import annotations

import datetime
import decimal
import math
from collections import Counter
from pathlib import Path

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(value):
    if isinstance(value, bool) or value is None:
        return value
    if isinstance(value, decimal.Decimal):
        value = float(value)
    if isinstance(value, int):
        return float(value) if abs(value) < 1 << 53 else value
    if isinstance(value, float):
        return None if math.isnan(value) else round(value, 6) + 0.0
    if isinstance(value, datetime.datetime):
        return value.replace(tzinfo=None).isoformat()
    if isinstance(value, datetime.date):
        return datetime.datetime(value.year, value.month, value.day).isoformat()
    if isinstance(value, (list, tuple)):
        return tuple(map(plain, value))
    return value


def oracle_rows(sql: str, sf_dir: str) -> tuple[list[str], Counter]:
    con = duckdb.connect()
    con.execute("set timezone='UTC'")
    for t in TABLES:
        at = Path(f"{sf_dir}/{t}.parquet")
        con.execute(f"create view {t} as select * from '{at}{'/*.parquet' if at.is_dir() else ''}'")
    got = con.execute(sql)
    names = [d[0] for d in got.description]
    order = sorted(range(len(names)), key=lambda i: names[i])
    return [names[i] for i in order], Counter(tuple(plain(r[i]) for i in order) for r in got.fetchall())


def spark_rows(df) -> tuple[list[str], Counter]:
    names = sorted(df.columns)
    return names, Counter(tuple(plain(r[n]) for n in names) for r in df.collect())


def difference(df, sql: str, sf_dir: str) -> str:
    """Empty if both agree."""
    (a, x), (b, y) = spark_rows(df), oracle_rows(sql, sf_dir)
    if a != b:
        return f"columns {a} and {b}"
    if x != y:
        return f"rows {sum(x.values())} and {sum(y.values())}; only here {list((x - y).items())[:3]}; only there {list((y - x).items())[:3]}"
    return ""
