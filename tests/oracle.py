"""Spark queries against their SQL in DuckDB, as multisets of rows."""

import glob
import os

import duckdb
import pandas as pd


def connect(sf_dir):
    con = duckdb.connect()
    for f in glob.glob(f"{sf_dir}/*.parquet"):
        con.sql(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return con


def rows(df: pd.DataFrame):
    def text(x):
        if x is None or x is pd.NA or (isinstance(x, float) and x != x):
            return "None"
        return repr(float(x)) if isinstance(x, (int, float)) and not isinstance(x, bool) else str(x)

    df = df[sorted(df.columns)].astype(object)
    return sorted(tuple(text(x.item() if hasattr(x, "item") else x) for x in r) for r in df.itertuples(index=False))
