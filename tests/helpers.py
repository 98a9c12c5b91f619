"""Comparison of a registered query with its DuckDB text."""

import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def duck(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        con.sql(f"create view {t} as select * from '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return con


def plain(value):
    if value is None or value != value:
        return None
    if isinstance(value, bool):
        return value
    if isinstance(value, (list, tuple)):
        return tuple(map(plain, value))
    if hasattr(value, "tolist"):
        return plain(value.tolist())
    if hasattr(value, "is_integer") or isinstance(value, int):
        return float(value)
    return float(value) if type(value).__name__ == "Decimal" else str(value)


def rows_of(df, columns):
    return sorted((tuple(plain(r[c]) for c in columns) for r in df), key=repr)


def same(spark_df, con, text):
    ours = spark_df.collect()
    theirs = con.sql(text)
    columns = sorted(theirs.columns)
    assert columns == sorted(spark_df.columns)
    want = [dict(zip(theirs.columns, r)) for r in theirs.fetchall()]
    return rows_of(ours, columns) == rows_of(want, columns)
