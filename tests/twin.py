"""Rows of a query and of its SQL twin, made comparable."""

import glob
import os
from decimal import Decimal

import duckdb


def plain(value):
    if isinstance(value, Decimal):
        value = float(value)
    return round(value, 9) if isinstance(value, float) else value


def duck(sf_dir: str, sql: str):
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for path in glob.glob(f"{sf_dir}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM read_parquet('{path}')")
    got = con.execute(sql)
    names = [d[0] for d in got.description]
    return sorted(names), sorted(repr([plain(dict(zip(names, row))[c]) for c in sorted(names)]) for row in got.fetchall())


def spark_rows(df):
    names = sorted(df.columns)
    return names, sorted(repr([plain(row[c]) for c in names]) for row in df.collect())
