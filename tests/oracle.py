"""Runs a query beside its SQL in DuckDB and compares rows."""

import glob
import os

import duckdb

SF = "/root/testdata/sf0.001"


def connection(sf: str = SF):
    con = duckdb.connect()
    for path in glob.glob(f"{sf}/*.parquet"):
        con.execute(f"create view {os.path.basename(path).split('.')[0]} as select * from '{path}'")
    return con


def tidy(v):
    if isinstance(v, float):
        return round(v, 5) + 0.0
    return tuple(v) if isinstance(v, list) else v


def compare(spark, query, sql: str, sf: str = SF) -> int:
    df = query(spark, sf)
    cur = connection(sf).execute(sql)
    names = [c[0] for c in cur.description]
    assert sorted(names) == sorted(df.columns)
    key = lambda r: tuple((x is None, str(x)) for x in r)
    ours = sorted((tuple(tidy(r[c]) for c in sorted(names)) for r in df.collect()), key=key)
    order = sorted(range(len(names)), key=lambda i: names[i])
    theirs = sorted((tuple(tidy(r[i]) for i in order) for r in cur.fetchall()), key=key)
    assert len(ours) == len(theirs)
    for a, b in zip(ours, theirs, strict=True):
        assert a == b
    return len(ours)
