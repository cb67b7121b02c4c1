"""Runs a registered query beside its DuckDB SQL and compares rows as multisets."""

import datetime
import decimal
import math
import os
from collections import Counter

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else round(v, 6)
    if isinstance(v, decimal.Decimal):
        return int(v) if v == v.to_integral_value() else round(float(v), 6)
    if isinstance(v, (list, tuple)):
        return tuple(plain(x) for x in v)
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None)
    return v


def sql_rows(sql, sf_dir):
    db = duckdb.connect()
    db.execute("SET TimeZone='UTC'")
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path}{'/*.parquet' if os.path.isdir(path) else ''}'")
    cursor = db.execute(sql)
    names = [d[0] for d in cursor.description]
    return names, cursor.fetchall()


def compare(spark, run, sql, sf_dir):
    df = run(spark, sf_dir)
    names, want = sql_rows(sql, sf_dir)
    order = sorted(names)
    assert sorted(df.columns) == order, (df.columns, names)
    got = Counter(tuple(plain(r[c]) for c in order) for r in df.collect())
    at = [names.index(c) for c in order]
    want = Counter(tuple(plain(r[i]) for i in at) for r in want)
    assert got == want, (list((got - want).items())[:3], list((want - got).items())[:3], sum(got.values()), sum(want.values()))
