"""Spark results against DuckDB's."""

import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        p = f"{sf_dir}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{p + '/*.parquet' if os.path.isdir(p) else p}'")
    return con


def value(v):
    return repr(round(v, 6)) if isinstance(v, float) else str(v)


def spark_rows(df):
    return sorted(tuple(map(value, r)) for r in df.select(sorted(df.columns)).collect())


def duck_rows(con, sql):
    r = con.execute(sql)
    names = [c[0] for c in r.description]
    order = [names.index(n) for n in sorted(names)]
    return sorted(names), sorted(tuple(value(row[i]) for i in order) for row in r.fetchall())


def assert_twin(df, con, sql):
    names, expected = duck_rows(con, sql)
    assert sorted(df.columns) == names
    assert spark_rows(df) == expected
