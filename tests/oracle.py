"""Comparison of a query's rows with its oracle's, by column names and independent of order."""

import glob
import os

import duckdb


def connect(d: str):
    c = duckdb.connect()
    c.execute("set TimeZone = 'UTC'")
    for p in glob.glob(f"{d}/*.parquet"):
        c.execute(f"create view {os.path.basename(p)[:-8]} as select * from '{p}'")
    return c


def _value(v):
    return round(v, 9) + 0.0 if isinstance(v, float) else tuple(v) if isinstance(v, list) else v


def same(frame, result) -> bool:
    names = sorted(frame.columns)
    found = [x[0] for x in result.description]
    assert sorted(found) == names
    at = [found.index(n) for n in names]
    ours = sorted((tuple(map(_value, r)) for r in frame.select(*(f"`{n}`" for n in names)).collect()), key=repr)
    theirs = sorted((tuple(_value(r[i]) for i in at) for r in result.fetchall()), key=repr)
    return ours == theirs
