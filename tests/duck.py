"""Runs a query's SQL in DuckDB over the same tables and compares whole rows."""

import os

import duckdb


def duck(sf_dir):
    con = duckdb.connect()
    for f in sorted(os.listdir(sf_dir)):
        con.sql(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{sf_dir}/{f}'")
    return con


def same(df, relation):
    names = sorted(df.columns)
    got = sorted((tuple(r[c] for c in names) for r in df.collect()), key=repr)
    want = sorted((tuple(r[relation.columns.index(c)] for c in names) for r in relation.fetchall()), key=repr)
    return names == sorted(relation.columns) and got == want
