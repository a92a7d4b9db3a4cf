"""Compares a query with its SQL over one scale factor."""

import glob
import math

import duckdb


def canonical(x):
    if isinstance(x, float):
        return "nan" if math.isnan(x) else round(x, 9) + 0.0
    return x


def check(df, sql, sf):
    db = duckdb.connect()
    for f in glob.glob(f"{sf}/*.parquet"):
        db.sql(f"CREATE VIEW {f.split('/')[-1][:-8]} AS SELECT * FROM '{f}'")
    want = db.sql(sql)
    names = sorted(want.columns)
    assert sorted(df.columns) == names
    picked = sorted((tuple(canonical(r[c]) for c in names) for r in df.collect()), key=repr)
    order = [want.columns.index(c) for c in names]
    held = sorted((tuple(canonical(r[i]) for i in order) for r in want.fetchall()), key=repr)
    assert len(picked) == len(held)
    assert picked == held, next((a, b) for a, b in zip(picked, held) if a != b)
