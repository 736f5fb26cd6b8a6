"""Runs a query and its SQL side by side, as the driver does."""

import glob
import os

import duckdb


def rows_of(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])

    def plain(v):
        return repr(round(v, 6) + 0.0) if isinstance(v, float) else str(v)

    return [columns[i] for i in order], sorted(tuple(plain(r[i]) for i in order) for r in rows)


def duck(sf_dir, sql):
    con = duckdb.connect()
    for p in glob.glob(f"{sf_dir}/*.parquet"):
        at = p if os.path.isfile(p) else f"{p}/*.parquet"
        con.sql(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{at}'")
    got = con.sql(sql)
    return rows_of(got.columns, got.fetchall())


def spark_rows(df):
    return rows_of(df.columns, df.collect())
