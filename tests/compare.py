"""Runs a query's SQL in DuckDB on the same files and compares rows, whatever their order."""

import glob
import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def database(sf_dir, **views):
    con = duckdb.connect()
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        if os.path.exists(path):
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path if os.path.isfile(path) else path + '/*.parquet'}'")
    return con


def plain(value):
    if isinstance(value, float):
        return round(value, 6)
    return float(value) if type(value).__name__ == "Decimal" else value


def rows(found):
    return sorted(repr(tuple(plain(v) for v in r)) for r in found)


def same(df, sql, con):
    names = sorted(df.columns)
    result = con.execute(sql)
    there = [d[0] for d in result.description]
    assert sorted(there) == names
    order = [there.index(c) for c in names]
    assert rows(tuple(r) for r in df.select(*names).collect()) == rows(tuple(r[k] for k in order) for r in result.fetchall())


def files(pattern):
    return glob.glob(pattern)
