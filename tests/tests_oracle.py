"""Holds a query against its SQL in DuckDB."""

import math
import os

import duckdb
import pandas as pd


def connect(sf_dir):
    c = duckdb.connect()
    c.execute("SET TimeZone='UTC'")
    for f in os.listdir(sf_dir):
        c.execute(f"create view {f[:-8]} as select * from read_parquet('{sf_dir}/{f}')")
    return c


def _plain(v):
    if v is None or v is pd.NaT or v is pd.NA or isinstance(v, float) and math.isnan(v):
        return None
    if isinstance(v, (bool, str)):
        return v
    if isinstance(v, float):
        return v
    return int(v) if type(v).__name__.startswith(("int", "uint", "Int")) else str(v)


def rows(pdf):
    columns = sorted(pdf.columns)
    return columns, sorted((tuple(_plain(v) for v in r) for r in pdf[columns].itertuples(index=False)), key=repr)


def same(spark, sf_dir, query, sql, connection):
    got, want = rows(query(spark, sf_dir).toPandas()), rows(connection.sql(sql).df())
    assert got[0] == want[0]
    assert len(got[1]) == len(want[1])
    for a, b in zip(got[1], want[1]):
        assert a == b
