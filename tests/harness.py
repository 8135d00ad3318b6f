"""Runs a query and its SQL on the same tables and compares all rows."""

from __future__ import annotations

import datetime
import decimal
import glob
import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def duck(sf_dir: str):
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        files = sorted(glob.glob(f"{path}/*.parquet")) if os.path.isdir(path) else [path]
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet({files})")
    return con


def plain(x):
    if isinstance(x, decimal.Decimal):
        return float(x)
    if isinstance(x, float):
        return round(x, 9)
    if isinstance(x, datetime.datetime):
        return x.replace(tzinfo=None)
    return x


def rows(columns: list[str], found) -> list:
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    key = lambda r: tuple((x is not None, str(type(x).__name__), x) for x in r)
    return sorted((tuple(plain(r[i]) for i in order) for r in found), key=key)


_KINDS = {"bigint": "BIGINT", "int": "INTEGER", "string": "VARCHAR", "double": "DOUBLE", "boolean": "BOOLEAN", "timestamp": "TIMESTAMP", "timestamp_ntz": "TIMESTAMP", "date": "DATE", "float": "FLOAT"}


def compare(spark, query, sql: str, sf_dir: str) -> str:
    """Empty if they agree."""
    df = query(spark, sf_dir)
    got = rows(df.columns, df.collect())
    con = duck(sf_dir)
    rel = con.execute(sql)
    names = [x[0] for x in rel.description]
    kinds = {x[0]: str(x[1]) for x in rel.description}
    want = rows(names, rel.fetchall())
    if sorted(df.columns) != sorted(names):
        return f"columns {df.columns} and {names}"
    if got != want:
        odd = [(a, b) for a, b in zip(got, want) if a != b][:2]
        return f"{len(got)} and {len(want)} rows; {str(odd)[:600]}"
    told = {c: (k, kinds[c]) for c, k in df.dtypes if _KINDS.get(k, k).upper() not in kinds[c].upper() and kinds[c].upper() not in ("NUMBER", "STRING", "DATETIME")}
    return f"kinds {told}" if told else ""
