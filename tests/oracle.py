"""Runs a query and its SQL twin and compares their rows."""

import duckdb
import pandas as pd

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connection(d=SF):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet'")
    return con


def rows(pdf):
    pdf = pdf[sorted(pdf.columns)]
    clean = lambda x: None if pd.isna(x) else (float(x) if isinstance(x, float) else (int(x) if hasattr(x, "item") and not isinstance(x, str) else x))
    return sorted((tuple(clean(x) for x in r) for r in pdf.astype(object).itertuples(index=False)), key=repr)


def same(spark, query, sql, d=SF):
    got, want = query(spark, d).toPandas(), connection(d).execute(sql).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)
