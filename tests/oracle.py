"""Comparing a Spark query with its SQL twin in DuckDB."""

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    return con


def assert_same(df, con, sql):
    columns = sorted(df.columns)
    got = con.execute(sql)
    names = [d[0] for d in got.description]
    assert sorted(names) == columns
    at = [names.index(c) for c in columns]
    theirs = sorted(repr(tuple(row[i] for i in at)) for row in got.fetchall())
    ours = sorted(repr(tuple(r[c] for c in columns)) for r in df.collect())
    assert ours == theirs
