"""Compares a query with its SQL as the driver does: columns by name, rows in any order."""

import glob
import os

import duckdb

DATA = os.environ.get("DELTAMP_DATA", "/root/testdata")


def connection(sf: str):
    c = duckdb.connect()
    for p in glob.glob(f"{DATA}/{sf}/*.parquet"):
        c.sql(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    return c


def normal(rows, columns):
    order = sorted(range(len(columns)), key=columns.__getitem__)
    value = lambda x: float(f"{x:.9g}") if isinstance(x, float) else x
    return sorted((tuple(value(r[i]) for i in order) for r in rows), key=str)


def differs(spark, name, query, sql, sf="sf0.001") -> str:
    df = query(spark, f"{DATA}/{sf}")
    got = normal([tuple(r) for r in df.collect()], df.columns)
    out = connection(sf).sql(sql)
    want = normal(out.fetchall(), out.columns)
    if sorted(df.columns) != sorted(out.columns):
        return f"{name}: columns {sorted(df.columns)} and {sorted(out.columns)}"
    if any("HUGEINT" in str(t) for t in out.types):
        return f"{name}: HUGEINT in {out.types}"
    if got != want:
        pair = next(((a, b) for a, b in zip(got, want) if a != b), None)
        return f"{name}: {len(got)} and {len(want)} rows; first difference {pair}"
    return ""
