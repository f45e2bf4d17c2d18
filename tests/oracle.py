"""Spark rows against DuckDB rows of the same query."""

import math

import duckdb
import pandas as pd

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def rows_of(pdf):
    cols = sorted(pdf.columns)

    def cell(v):
        if v is None or pd.isna(v) is True:
            return "None"
        return f"{v:.9g}" if isinstance(v, float) and math.isfinite(v) else str(v)

    return cols, sorted(tuple(cell(v) for v in r) for r in pdf[cols].itertuples(index=False))


def connection(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


def same(spark, sf, run, sql):
    got, want = rows_of(run(spark, sf).toPandas()), rows_of(connection(sf).sql(sql).df())
    assert got[0] == want[0]
    assert got[1] == want[1]
