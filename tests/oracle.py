"""Compares a query with its SQL in DuckDB on the smallest tables."""

import numbers
from pathlib import Path

import duckdb
import pandas as pd

SF = "/root/testdata/sf0.001"


def connection():
    con = duckdb.connect()
    for p in Path(SF).glob("*.parquet"):
        con.sql(f"create view {p.stem} as from '{p}'")
    return con


def rows(df: pd.DataFrame) -> list:
    df = df[sorted(df.columns)]

    def plain(v):
        if not hasattr(v, "__len__") and pd.isna(v):
            return ""
        number = isinstance(v, numbers.Number) and not isinstance(v, bool)
        return f"{float(v):.12g}" if number else str(v)

    return sorted(tuple(map(plain, r)) for r in df.itertuples(index=False))


def same(spark, name, queries, sql) -> None:
    got, want = queries[name](spark, SF).toPandas(), connection().sql(sql[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)
