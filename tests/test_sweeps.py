"""Sweeps take every fold of every repetition, and the choice of parameters sees their averages."""

import pytest
from pyspark.sql import functions as F

from locpref.operators import baselines
from locpref.plans import experiment, queries
from locpref.sources.tables import event_visits


def test_registered_sweeps_take_whole_repetitions(spark, small, monkeypatch):
    seen = []
    monkeypatch.setattr(queries, "_AVERAGES", {})
    monkeypatch.setattr(experiment, "sweep", lambda v, grid, folds=10, runs=1, **how: seen.append((len(grid), folds, runs)) or v.limit(0).selectExpr("1 AS a_mean"))
    monkeypatch.setattr(experiment, "averaged", lambda rows: rows, raising=False)
    for name in queries.SWEEPS:
        queries.queries()[name](spark, small)
    large = {"sweep_width_months", "sweep_unknown_lineitem", "sweep_location"}
    assert seen == [(len(grid), 10, 10 * (queries.REPEATS_LARGE if name in large else queries.REPEATS)) for name, (_, grid, _) in queries.SWEEPS.items()]
    assert queries.REPEATS >= 10 and queries.REPEATS_LARGE >= 1


def test_ten_folds_hold_out_every_user_and_are_averaged(spark, small):
    v = event_visits(spark, small)
    cells = experiment.event_cells(v, 6, hourly=False)
    held = experiment.repeat(cells, 10, 1, 1.0).where("held = 1").select("run", "user_id").distinct()
    assert held.count() == cells.select("user_id").distinct().count()
    rows = experiment.sweep(v, [{"width": 6, "eps": 10.0, "unknown": 0.5}], runs=10, rounds=1, methods=("plain", "majority")).cache()
    got = {r.method: r for r in experiment.averaged(rows).collect()}
    for r in rows.groupBy("method").agg(F.avg("reconstruction").alias("a"), F.count("*").alias("n")).collect():
        assert (got[r.method].n, r.n) == (10, 10) and got[r.method].reconstruction_mean == pytest.approx(r.a)


def test_baselines_by_run_equal_single_runs(spark, small):
    t = queries.triples(spark, small)
    parts = [t, t.where("user_id % 2 = 0")]
    both = parts[0].withColumn("run", F.lit(0)).unionByName(parts[1].withColumn("run", F.lit(1))).cache()
    for f in (baselines.cf_user, baselines.cf_item, lambda c, r, **k: baselines.majority(c, r, "bias", **k)):
        got = f(both.select("run", "user_id", "item_id"), both, keys=("run",)).collect()
        for n, part in enumerate(parts):
            want = {(r.user_id, r.item_id): r.score for r in f(part.select("user_id", "item_id"), part).collect()}
            assert {(r.user_id, r.item_id): r.score for r in got if r.run == n} == pytest.approx(want)


def test_choice_on_averages_keeps_a_method_below_the_target(spark):
    rows = lambda name, xs: spark.createDataFrame(xs, f"method string, {name}, reconstruction_mean double")
    widths = rows("width int", [("plain", 2, 0.7), ("plain", 6, 0.8), ("private", 2, 0.5), ("private", 6, 0.4)])
    levels = rows("eps double", [("plain", 0.1, 0.8), ("plain", 1.0, 0.8), ("private", 0.1, 0.4), ("private", 1.0, 0.5)])
    shares = rows("unknown double", [("plain", 0.1, 0.8), ("plain", 0.5, 0.6), ("plain", 0.9, 0.5), ("private", 0.1, 0.5)])
    assert sorted(map(tuple, experiment.choice(widths, levels, shares, 0.03, 0.55).collect())) == [("plain", 6, 0.1, 0.5), ("private", 2, 1.0, None)]


@pytest.mark.parametrize("sim", ["cosine", "pearson", "jaccard"])
def test_dense_neighbours_equal_the_join(spark, sim, monkeypatch):
    """Users with equal ratings, ties, missing cells and several runs: the same neighbours as a join of all pairs, in lists of a few."""
    import random

    monkeypatch.setattr(baselines, "DENSE_ROWS", 7)
    rng = random.Random(6)
    rows = [(run, u, f"i{i}", float((u * 7 + i * (1 + u % 5)) % 3 > 0)) for run in range(2) for u in range(60) for i in range(6) if rng.random() < 0.8 or u < 20]
    t = spark.createDataFrame(rows, "run int, user_id long, item_id string, rating double")
    got = {(r.run, r.a, r.b): r.s for r in baselines._top(t, "user_id", 4, sim, 2, ("run",)).collect()}
    monkeypatch.setattr(baselines, "MAX_DENSE", 0)
    want = {(r.run, r.a, r.b): r.s for r in baselines._top(t, "user_id", 4, sim, 2, ("run",)).collect()}
    assert got == pytest.approx(want) and len(want) > 300


def test_cf_user_makes_no_row_for_each_pair(spark, small):
    t = queries.triples(spark, small)
    plan = baselines.cf_user(t.select("user_id", "item_id"), t)._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in plan and "common" not in plan


def test_settings_that_differ_in_eps_share_the_plain_fit(spark, small, monkeypatch):
    seen, fit = [], experiment.factorization.fit_plain
    monkeypatch.setattr(experiment.factorization, "fit_plain", lambda t, *a: seen.append(t.select("run").distinct().count()) or fit(t, *a))
    grid = [{"width": 6, "eps": e, "unknown": 0.5} for e in (0.1, 10.0)]
    rows = experiment.sweep(event_visits(spark, small), grid, folds=2, runs=2, rounds=1, methods=("plain",)).collect()
    assert seen == [2] and sorted((r.eps, r.run) for r in rows) == [(0.1, 0), (0.1, 1), (10.0, 2), (10.0, 3)]
    assert len({r.reconstruction for r in rows if r.run in (0, 2)}) == 1


def test_array_draws_equal_the_columns(spark):
    """Keys of one and of two blocks, with letters of several bytes."""
    from locpref.functions import draws, hashing

    texts = [f"{u}:{'x' * (u % 70)}é@{u % 12}" for u in range(300)]
    t = spark.createDataFrame([(n, x) for n, x in enumerate(texts)], "n int, t string")
    keys = draws.Keys([x.encode() for x in texts])
    for run in (7, 899):
        want = [r[0] for r in t.select("n", hashing.uniform(42, "lap", F.lit(run), F.col("t"), F.lit(3), F.lit(1)).alias("u")).orderBy("n").select("u").collect()]
        assert keys.uniform([f"42:lap:{run}:".encode()], b":3:1")[0].tolist() == want
    assert not draws.laplace(keys.uniform([b"42:lap:"])[0], 0.0).any()


@pytest.mark.parametrize("empty", [0, 10])
def test_fits_by_blocks_equal_fits_by_joins(spark, small, monkeypatch, empty):
    """All fitted methods, users whose ratings are all held, settings alike, a cut repetition, matrices and lists of cells."""
    from locpref.operators import blocks

    monkeypatch.setattr(blocks, "MOST_EMPTY", empty)
    monkeypatch.setattr(blocks, "UNIT_CELLS", 300)
    grid = [{"width": w, "eps": e, "unknown": u} for w, e, u in ((12, 10.0, 0.9), (12, 0.01, 0.9), (6, 2.0, 0.5))]
    ask = lambda: {(r.method, r.width, r.eps, r.run): (r.fpr, r.recall, r.reconstruction) for r in experiment.sweep(event_visits(spark, small).where("user_id % 3 = 0"), grid, folds=2, runs=3, rounds=2, methods=("plain", *experiment.PROTECT)).collect()}
    got = ask()
    monkeypatch.setattr(experiment, "FEW_RUNS", 1000)
    want = ask()
    assert len(want) == 7 * 3 * 3 and got == want


def test_a_sweep_writes_no_row_for_each_run_and_cell(spark, small, monkeypatch):
    monkeypatch.setattr(experiment, "repeat", lambda *a: pytest.fail("cells were written once for each run"))
    rows = experiment.sweep(event_visits(spark, small), [queries.BASE], runs=10, rounds=1)
    assert rows.count() == 20


def test_draws_for_some_pairs_equal_those_for_all():
    """Prefixes of two lengths, keys of one and two blocks, more rows than a piece."""
    import numpy as np

    from locpref.functions import draws

    keys = draws.Keys([f"{u}:{'é' * (u % 30)}@{u % 12}".encode() for u in range(draws.PIECE // 8 + 5)])
    heads = [f"42:bit_flip:{n}:".encode() for n in (8, 9, 10, 11)]
    whole = keys.uniform(heads, b":3")
    assert (whole == keys.bits(heads, b":3") / 2.0**52).all()
    which, rows = np.nonzero(whole < 0.9)
    assert (keys.uniform_at(heads, b":3", which, rows) == whole[which, rows]).all()


@pytest.mark.parametrize("p", [0.02, 0.4, 0.97])
def test_noisy_bits_hash_the_lesser_part_only(p, monkeypatch):
    """A bit is open, or a coin where it is flipped; a draw that can change nothing is not made."""
    import numpy as np

    from locpref.functions import draws
    from locpref.operators import blocks

    plan = blocks.Plan(((0, 0.5, 1.0),), (("plain", None, False),), (0,), ([f"i{n}" for n in range(20)],), 10, 20, 3, 42)
    item, users, hashed = np.tile(np.arange(20), 60), np.repeat(np.arange(60), 20), []
    unit = blocks.Unit(plan, 0, 1, users, item, np.ones(1200), np.ones(1200, int))
    at = draws.Keys.uniform_at
    monkeypatch.setattr(draws.Keys, "uniform_at", lambda self, *a: hashed.append(len(a[-1])) or at(self, *a))
    got = unit.bits(2, p)
    flip, coin = (unit.cells.uniform([f"42:bit_{w}:{n}:".encode() for n in range(10, 20)], b":2") for w in ("flip", "coin"))
    assert (got == np.where(flip < p, coin < 0.5, 1.0)).all()
    assert hashed == [int((coin >= 0.5).sum() if p > 0.5 else (flip < p).sum())]


def test_a_sweep_passes_its_cells_once_a_round_and_once_to_decide(spark, small, monkeypatch):
    from locpref.operators import blocks

    passes, summed = [], blocks._summed
    monkeypatch.setattr(blocks, "_summed", lambda units, work: passes.append(work) or summed(units, work))
    experiment.sweep(event_visits(spark, small), [queries.BASE], runs=10, rounds=3)
    assert len(passes) == 4


def test_votes_by_blocks_equal_votes_by_joins(spark, small, monkeypatch):
    """Neighbours and majorities: ties, lists of a few users, users whose ratings are all held, settings alike, a cut repetition."""
    from locpref.operators import votes

    monkeypatch.setattr(votes, "ROWS", 7)
    monkeypatch.setattr(votes, "COLUMNS", 30)
    grid = [{"width": w, "eps": e, "unknown": u} for w, e, u in ((12, 10.0, 0.95), (12, 0.01, 0.95), (6, 2.0, 0.5))]
    visits = event_visits(spark, small).where("user_id % 3 = 0 and event_id % 2 = 0")
    ask = lambda: {(r.method, r.width, r.eps, r.run): (r.fpr, r.recall, r.reconstruction) for r in experiment.sweep(visits, grid, folds=2, runs=3, methods=votes.METHODS).collect()}
    repeat = experiment.repeat
    monkeypatch.setattr(experiment, "repeat", lambda *a: pytest.fail("cells were written once for each run"))
    got = ask()
    monkeypatch.setattr(experiment, "repeat", repeat)
    monkeypatch.setattr(experiment, "FEW_RUNS", 1000)
    want = ask()
    assert len(want) == 3 * 3 * 3 and got == want
