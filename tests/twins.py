"""Runs a query and its DuckDB twin and compares their rows."""

from __future__ import annotations

import math
import os
from glob import glob

import duckdb
import pandas as pd


def views(folder: str) -> duckdb.DuckDBPyConnection:
    c = duckdb.connect()
    c.sql("SET timezone = 'UTC'")
    for f in glob(f"{folder}/*.parquet"):
        c.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return c


def rows_of(df: pd.DataFrame) -> list[tuple]:
    df = df[sorted(df.columns)].astype(object)

    def plain(v):
        if v is None or v is pd.NaT or v is pd.NA or isinstance(v, float) and math.isnan(v):
            return None
        if isinstance(v, bool) or type(v).__name__ == "bool_" or type(v).__name__ == "bool":
            return str(bool(v))
        if isinstance(v, pd.Timestamp):
            return str(v.tz_localize(None))
        return round(float(v), 6) + 0.0 if hasattr(v, "__float__") and not isinstance(v, str) else str(v)

    return sorted((tuple(map(plain, r)) for r in df.itertuples(index=False)), key=str)


def assert_twin(spark, folder: str, query, sql: str) -> None:
    got = query(spark, folder).toPandas()
    want = views(folder).sql(sql).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows_of(got) == rows_of(want)
