"""Compare a Spark result with DuckDB's, without regard to the order of rows."""

import math

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations"


def connect(folder):
    con = duckdb.connect()
    for t in TABLES.split():
        con.sql(f"create view {t} as select * from '{folder}/{t}.parquet'")
    return con


def shown(value):
    if value is None or isinstance(value, float) and math.isnan(value):
        return "null"
    return f"{value:.6g}" if isinstance(value, float) else str(value)


def table_of(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(tuple(shown(r[i]) for i in order) for r in rows)


def assert_same(df, con, sql):
    made = con.sql(sql)
    assert sorted(df.columns) == sorted(made.columns)
    assert table_of(df.columns, [tuple(r) for r in df.collect()]) == table_of(made.columns, made.fetchall())
