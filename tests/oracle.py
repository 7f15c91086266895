"""Runs a query on Spark and its SQL twin on DuckDB, and compares the rows without order."""

import os

import duckdb
import pandas as pd


def connect(sf_dir: str):
    con = duckdb.connect()
    for name in os.listdir(sf_dir):
        con.execute(f"CREATE VIEW {name.split('.')[0]} AS SELECT * FROM '{sf_dir}/{name}'")
    return con


def _plain(df: pd.DataFrame) -> pd.DataFrame:
    df = df[sorted(df.columns)].copy()
    for c in df.columns:
        if df[c].dtype.kind in "fiub":
            df[c] = df[c].astype(float).round(6)
        else:
            try:
                df[c] = df[c].astype(float).round(6)
            except (TypeError, ValueError):
                df[c] = df[c].astype(str)
    return df.sort_values(list(df.columns)).reset_index(drop=True)


def same(spark, sf_dir: str, query, sql: str) -> None:
    got, want = _plain(query(spark, sf_dir).toPandas()), _plain(connect(sf_dir).sql(sql).df())
    assert list(got.columns) == list(want.columns)
    assert len(got) == len(want)
    pd.testing.assert_frame_equal(got, want, check_dtype=False, atol=3e-5, rtol=1e-6)
