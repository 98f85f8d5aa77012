"""Runs a query's SQL in DuckDB over the same tables and compares whole rows."""

import os

import duckdb


def duck(sf_dir):
    con = duckdb.connect()
    for f in sorted(os.listdir(sf_dir)):
        con.sql(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{sf_dir}/{f}'")
    return con


def rows(df, columns=None):
    columns = sorted(columns or df.columns)
    return sorted((tuple(r) for r in df.select(columns).collect()), key=repr)


def sql_rows(sql, sf_dir):
    got = duck(sf_dir).sql(sql)
    names = sorted(got.columns)
    return names, sorted((tuple(r[got.columns.index(c)] for c in names) for r in got.fetchall()), key=repr)
