"""Run a catalogue query and its SQL over the same tables and compare rows."""

import math
import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf):
    c = duckdb.connect()
    c.execute("set timezone='UTC'")
    for t in TABLES:
        p = f"{sf}/{t}.parquet"
        c.execute(f"create view {t} as select * from '{p + '/*.parquet' if os.path.isdir(p) else p}'")
    return c


def shown(x):
    if x is None or isinstance(x, float) and math.isnan(x):
        return "~"
    if isinstance(x, float):
        return repr(round(x, 6) + 0.0)
    return str(x)


def rows_of(df):
    cols = sorted(df.columns)
    return cols, sorted(tuple(shown(r[c]) for c in cols) for r in df.collect())


def sql_rows(connection, sql):
    got = connection.sql(sql)
    cols, at = sorted(got.columns), [got.columns.index(c) for c in sorted(got.columns)]
    return cols, sorted(tuple(shown(r[i]) for i in at) for r in got.fetchall())
