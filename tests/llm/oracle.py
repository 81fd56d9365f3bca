"""Runs a query's SQL in DuckDB over given tables (dicts of name to rows and DuckDB columns)."""

import math
import os

import duckdb

TABLES = "documents embeddings pages benchmark labels conversations".split()


def plain(x):
    return "nan" if isinstance(x, float) and math.isnan(x) else x


def rows_of(df, columns=None):
    columns = columns or sorted(df.columns)
    return sorted((tuple(plain(x) for x in r) for r in df.select(*columns).collect()), key=repr)


def sql_rows(sql, folder):
    con = duckdb.connect()
    for t in TABLES:
        path = f"{folder}/{t}.parquet"
        if os.path.exists(path):
            con.execute(f"create view {t} as select * from '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    got = con.execute(sql)
    names = [d[0] for d in got.description]
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted((tuple(plain(r[i]) for i in order) for r in got.fetchall()), key=repr)
