"""Rows of a query and of its SQL in a form that can be compared."""

import math

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return c


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else f"f{round(v, 6) + 0.0}"
    return None if v is None else str(v)


def rows_of(df):
    cols = sorted(df.columns)
    return cols, sorted(str(tuple(plain(r[c]) for c in cols)) for r in df.collect())


def sql_rows(con, sql):
    rel = con.sql(sql)
    order = sorted(range(len(rel.columns)), key=lambda i: rel.columns[i])
    return [rel.columns[i] for i in order], sorted(str(tuple(plain(r[i]) for i in order)) for r in rel.fetchall())
