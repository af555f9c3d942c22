"""Compare a Spark query with its SQL on DuckDB: columns by name, rows in any order."""

import datetime
import decimal
import time

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def duck(sf_dir):
    c = duckdb.connect()
    c.sql("set timezone='UTC'")
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    return c


def plain(v):
    if isinstance(v, (list, tuple)):
        return tuple(plain(x) for x in v)
    if isinstance(v, dict):
        return tuple((k, plain(x)) for k, x in v.items())
    if isinstance(v, decimal.Decimal):
        return float(v) if v % 1 else int(v)
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None).isoformat()
    return v


def differences(spark, sf_dir, query, sql):
    began = time.time()
    df = query(spark, sf_dir)
    cols = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=repr)
    took = time.time() - began
    rel = duck(sf_dir).sql(sql)
    order = sorted(range(len(rel.columns)), key=lambda i: rel.columns[i])
    if sorted(rel.columns) != cols:
        return [("columns", cols, sorted(rel.columns))], len(got), took
    want = sorted((tuple(plain(r[i]) for i in order) for r in rel.fetchall()), key=repr)
    bad = [(a, b) for a, b in zip(got, want) if repr(a) != repr(b)]
    if len(got) != len(want):
        bad.append(("rows", len(got), len(want)))
    return bad, len(got), took
