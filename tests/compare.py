"""Rows of a Spark query beside rows of DuckDB SQL on the same tables."""

from __future__ import annotations

import glob

import duckdb
import pandas as pd

KINDS = {"BIGINT": "bigint", "INTEGER": "int", "VARCHAR": "string", "DOUBLE": "double", "BOOLEAN": "boolean", "TIMESTAMP": "timestamp_ntz", "FLOAT": "float", "DATE": "date"}


def tables(directory: str) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    for f in glob.glob(f"{directory}/*.parquet"):
        con.sql(f"create view {f.split('/')[-1][:-8]} as select * from read_parquet('{f}')")
    return con


def rows(df: pd.DataFrame, cols: list[str]) -> list[str]:
    def plain(x):
        if x is None or pd.isna(x):
            return None
        return float(x) if isinstance(x, float) else x.isoformat() if hasattr(x, "isoformat") else x

    return sorted(map(repr, zip(*[[plain(x) for x in df[c].astype(object)] for c in cols], strict=True)))


def assert_same(spark_df, con: duckdb.DuckDBPyConnection, sql: str) -> None:
    rel = con.sql(sql)
    cols = sorted(spark_df.columns)
    assert cols == sorted(rel.columns)
    kinds = dict(spark_df.dtypes)
    for name, kind in zip(rel.columns, map(str, rel.types), strict=True):
        assert KINDS.get(kind, kind) == kinds[name], f"{name}: {kind} in SQL, {kinds[name]} in Spark"
    a, b = rows(spark_df.toPandas(), cols), rows(rel.df(), cols)
    assert len(a) == len(b)
    assert a == b
