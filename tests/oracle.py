"""Compares a query's rows with its SQL on the same tables, as the gate does."""

import math

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    return con


def norm(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 6) + 0.0
    return v


def differences(df, sql, con):
    """None if equal, else a short account."""
    out = con.sql(sql)
    names = sorted(out.columns)
    if names != sorted(df.columns):
        return f"columns {sorted(df.columns)} against {names}"
    at = [out.columns.index(n) for n in names]
    want = sorted((tuple(norm(r[i]) for i in at) for r in out.fetchall()), key=repr)
    got = sorted((tuple(norm(r[n]) for n in names) for r in df.collect()), key=repr)
    if len(got) != len(want):
        return f"{len(got)} rows against {len(want)}"
    bad = [(a, b) for a, b in zip(got, want) if a != b]
    return f"{len(bad)} of {len(got)} rows differ, such as {bad[0]}" if bad else None
