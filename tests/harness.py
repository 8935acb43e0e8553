"""Runs a query and its SQL and compares them as the driver does."""

from __future__ import annotations

import math

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str):
    c = duckdb.connect()
    c.execute("SET TimeZone='UTC'")
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return c


def _plain(x):
    if isinstance(x, float):
        return "nan" if math.isnan(x) else repr(x + 0.0)
    return repr(x)


def rows_of(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(tuple(_plain(r[i]) for i in order) for r in rows)


def compare(spark, sf_dir: str, query, sql: str) -> list:
    """Empty if equal, else the first differences."""
    df = query(spark, sf_dir)
    got = rows_of(df.columns, [tuple(r) for r in df.collect()])
    con = connect(sf_dir)
    rel = con.execute(sql)
    names = [x[0] for x in rel.description]
    want = rows_of(names, rel.fetchall())
    if sorted(df.columns) != sorted(names):
        return [("columns", df.columns, names)]
    if len(got) != len(want):
        return [("rows", len(got), len(want), [x for x in got if x not in want][:2], [x for x in want if x not in got][:2])]
    return [(a, b) for a, b in zip(got, want, strict=True) if a != b][:3]
