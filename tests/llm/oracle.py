"""Runs a query's SQL by DuckDB on the same tables and compares whole results."""

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def rows_of(sql: str, sf_dir: str):
    con = duckdb.connect()
    con.sql("SET threads = 4")
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    out = con.sql(sql)
    return out.columns, sorted(out.fetchall(), key=repr)


def same(df, sql: str, sf_dir: str) -> None:
    names, want = rows_of(sql, sf_dir)
    assert sorted(names) == sorted(df.columns)
    got = sorted((tuple(r) for r in df.select(*names).collect()), key=repr)
    assert len(got) == len(want)
    assert got == want
