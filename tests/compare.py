"""Compares a Spark result with DuckDB's on the same tables, as the driver does: columns by name, rows in any order."""

import math

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    return con


def normal(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else f"{v:.6g}"
    if isinstance(v, (list, tuple)):
        return tuple(normal(x) for x in v)
    return v if v is None or isinstance(v, (bool, int, str)) else str(v)


def same(df, sql, con):
    rel = con.sql(sql)
    names = sorted(rel.columns)
    assert names == sorted(df.columns), (names, sorted(df.columns))
    order = [rel.columns.index(c) for c in names]
    want = sorted([tuple(normal(r[i]) for i in order) for r in rel.fetchall()], key=str)
    got = sorted([tuple(normal(r[c]) for c in names) for r in df.collect()], key=str)
    assert len(got) == len(want), (len(got), len(want))
    for g, w in zip(got, want):
        assert g == w, (names, g, w)
