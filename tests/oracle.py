"""Runs a registered query in Spark and its SQL in DuckDB on the same files and compares the rows."""

import math
import os

import duckdb

DATA = os.environ.get("TESTDATA_DIR", "/root/testdata")
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(x):
    if isinstance(x, float):
        return "nan" if math.isnan(x) else round(x, 6) + 0.0
    if hasattr(x, "asDict"):
        return tuple(plain(v) for v in x)
    if isinstance(x, dict):
        return tuple(plain(v) for v in x.values())
    if isinstance(x, (list, tuple)):
        return tuple(plain(v) for v in x)
    if hasattr(x, "tzinfo"):
        return str(x.replace(tzinfo=None))
    return x


def duck_rows(sql: str, sf: str):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{sf}/{t}.parquet'")
    found = con.execute(sql)
    return [d[0] for d in found.description], found.fetchall()


def compare(spark, query, sql: str, sf: str) -> str:
    """Empty if equal, else what differs first."""
    df = query(spark, f"{DATA}/{sf}")
    names = sorted(df.columns)
    mine = sorted((tuple(plain(r[c]) for c in names) for r in df.collect()), key=repr)
    duck_names, rows = duck_rows(sql, sf)
    if sorted(duck_names) != names:
        return f"columns: {names} {sorted(duck_names)}"
    at = [duck_names.index(c) for c in names]
    theirs = sorted((tuple(plain(r[i]) for i in at) for r in rows), key=repr)
    if len(mine) != len(theirs):
        return f"rows: {len(mine)} {len(theirs)}"
    for a, b in zip(mine, theirs, strict=True):
        if a != b:
            return f"row: {str(a)[:400]} | {str(b)[:400]}"
    return ""
