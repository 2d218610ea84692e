"""Run a query and its SQL on the same Parquet files and compare rows."""

from __future__ import annotations

import glob
import math
import os

import duckdb


def connection(sf_dir: str):
    con = duckdb.connect()
    con.execute("SET TimeZone='UTC'")
    for f in glob.glob(f"{sf_dir}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return con


def plain(v) -> str:
    if isinstance(v, float):
        return "nan" if math.isnan(v) else repr(v + 0.0)
    if isinstance(v, (list, tuple)):
        return "[" + ",".join(plain(x) for x in v) + "]"
    return str(v)


def rows_of_spark(df) -> tuple[list[str], list[str]]:
    columns = sorted(df.columns)
    return columns, sorted("|".join(plain(r[c]) for c in columns) for r in df.collect())


def rows_of_sql(con, text: str) -> tuple[list[str], list[str]]:
    cursor = con.execute(text)
    names = [d[0] for d in cursor.description]
    columns = sorted(names)
    at = [names.index(c) for c in columns]
    return columns, sorted("|".join(plain(r[k]) for k in at) for r in cursor.fetchall())
