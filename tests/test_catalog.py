"""Every registered query that has SQL, against it: names, types and values."""

import pytest

from locpref.plans import oracles, queries

from .oracle import connect, differences

DIR = "/root/testdata/sf0.001"
SQL = oracles.oracle_sql()
TYPES = {"bigint": "BIGINT", "int": "INTEGER", "double": "DOUBLE", "string": "VARCHAR", "boolean": "BOOLEAN"}


@pytest.fixture(scope="module")
def con():
    return connect(DIR)


#: Experiments of many fits: their SQL is compared once with fewer repetitions and settings (``test_sweeps_equal_sql``).
SWEPT = {*queries.SWEEPS, "choose_parameters", "gap_pivot", "utility_slope"}


@pytest.mark.parametrize("name", sorted(SQL.keys() - SWEPT))
def test_equals_sql(name, spark, con):
    df = queries.queries()[name](spark, DIR)
    out = con.sql(SQL[name])
    assert {n: TYPES[t] for n, t in df.dtypes} == {n: str(t) for n, t in zip(out.columns, out.types)}
    assert differences(df, SQL[name], con) is None


def test_every_sql_has_a_query():
    assert SQL.keys() <= queries.queries().keys()


@pytest.mark.parametrize("name", sorted(SWEPT))
def test_sweeps_equal_sql(name, spark, con, monkeypatch):
    """The registered sweeps with one repetition, three folds, two settings and two rounds."""
    small = {n: (carrier, grid[:: max(1, len(grid) - 1)], how) for n, (carrier, grid, how) in queries.SWEEPS.items()}
    for module in (queries, oracles):
        for key, value in (("SWEEPS", small), ("FOLDS", 3), ("REPEATS", 1), ("REPEATS_LARGE", 1), ("SWEEP_ROUNDS", 2)):
            monkeypatch.setattr(module, key, value)
    monkeypatch.setattr(queries, "_AVERAGES", {})
    df = queries.queries()[name](spark, DIR)
    assert differences(df, oracles.oracle_sql()[name], con) is None


@pytest.mark.parametrize("name", ["flip_probability_grid", "ledger_totals", "privacy_audit", "traffic"])
def test_results_follow_a_given_table(name, spark, tmp_path):
    """These read customers or events: with half of the rows there, the results differ."""
    for t in ("customer", "events"):
        rows = spark.read.parquet(f"{DIR}/{t}.parquet")
        rows.where(f"{rows.columns[0]} % 2 = 0").write.parquet(f"{tmp_path}/{t}.parquet")
    q = queries.queries()[name]
    assert sorted(map(str, q(spark, DIR).collect())) != sorted(map(str, q(spark, str(tmp_path)).collect()))
