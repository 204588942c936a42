"""Compares a query with its SQL in DuckDB, as multisets of rows with columns by name."""

from collections import Counter

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def duck(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return con


def differences(df, con, sql):
    names = sorted(df.columns)
    got = Counter(tuple(r[c] for c in names) for r in df.collect())
    rel = con.sql(sql)
    assert sorted(rel.columns) == names, (rel.columns, names)
    at = [rel.columns.index(c) for c in names]
    want = Counter(tuple(r[i] for i in at) for r in rel.fetchall())
    return sum((got - want).values()), sum((want - got).values()), sum(got.values())
