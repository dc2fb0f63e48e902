"""Rows of a query and of its DuckDB twin in one comparable form."""

import duckdb
import pandas as pd

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return con


def _cell(v):
    if v is None or v is pd.NaT or v is pd.NA or (isinstance(v, float) and v != v):
        return ""
    if isinstance(v, float):
        return f"{v:.5g}"
    return str(v)


def rows(df):
    df = df[sorted(df.columns)].astype(object)
    return sorted(df.columns), sorted(tuple(map(_cell, r)) for r in df.itertuples(index=False))
