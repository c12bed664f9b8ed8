"""Compares a query's rows with those of its SQL on the same tables."""

import duckdb
import pandas as pd

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return con


def rows(frame):
    columns = sorted(frame.columns)
    text = lambda v: "none" if v is None or v is pd.NA or v is pd.NaT or v != v else f"{float(v):.9g}" if isinstance(v, int | float) and not isinstance(v, bool) else str(v)
    return columns, sorted(tuple(text(v) for v in r) for r in frame[columns].astype(object).itertuples(index=False))


def same(spark_frame, sql_frame):
    a, b = rows(spark_frame), rows(sql_frame)
    assert a[0] == b[0]
    assert len(a[1]) == len(b[1])
    assert a[1] == b[1]
