"""Runs a query and its SQL on the same tables and compares the rows without order."""

import math

import duckdb
import pandas as pd

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def cell(v):
    if v is None or v is pd.NA or v is pd.NaT or (isinstance(v, float) and math.isnan(v)):
        return ""
    if isinstance(v, float):
        return "0" if abs(v) < 5e-7 else f"{v:.6f}".rstrip("0").rstrip(".")
    return str(v)


def rows(columns, values):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(tuple(cell(r[i]) for i in order) for r in values)


def compare(df, sql, sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    got = con.execute(sql)
    names = [d[0] for d in got.description]
    assert sorted(df.columns) == sorted(names)
    a, b = rows(df.columns, [tuple(r) for r in df.collect()]), rows(names, got.fetchall())
    assert a == b, f"{len(a)} and {len(b)} rows; only Spark {list(set(a) - set(b))[:3]}; only SQL {list(set(b) - set(a))[:3]}"
