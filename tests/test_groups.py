"""Item vectors that are too large for all runs at once: the runs are fitted in groups, without a row for each run and cell."""

import pytest

from locpref.functions import lanes
from locpref.operators import blocks
from locpref.plans import experiment, queries
from locpref.sources.rounds import Rounds
from locpref.sources.tables import event_visits


def test_runs_of_many_items_are_fitted_in_groups(spark, small, monkeypatch):
    grid = [{"width": 6, "eps": e, "unknown": 0.5} for e in (0.5, 10.0)]
    ask = lambda: {(r.method, r.eps, r.run): (r.fpr, r.recall, r.reconstruction) for r in experiment.sweep(event_visits(spark, small), grid, folds=3, runs=5, rounds=2).collect()}
    want = ask()
    monkeypatch.setattr(blocks, "MAX_VECTORS", 2 * 2 * 8 * lanes.ROOM * 20)  # two runs
    monkeypatch.setattr(experiment, "repeat", lambda *a: pytest.fail("cells were written once for each run"))
    seen, make = [], blocks._measured
    monkeypatch.setattr(blocks, "_measured", lambda data, plan, rounds, groups, known: seen.append(groups) or make(data, plan, rounds, groups, known))
    assert ask() == want and len(want) == 20
    assert len(seen) > 4 and sorted((n, rep, k) for some in seen for n, rep, a, b in some for k in range(a, b)) == [(n, rep, k) for n in (0, 1) for rep in (0, 1) for k in range(3 - rep)]


@pytest.mark.parametrize("hourly", [False, True])
def test_cells_of_vectors_drawn_once_are_those_of_draws_by_cell(spark, small, hourly):
    visits = event_visits(spark, small)
    items, cells = experiment.Cells(Rounds(spark, "cells"), visits, hourly, 42, "hours").of(6, "category")
    want = experiment.event_cells(visits, 6, hourly=hourly)
    rows = lambda t: sorted(map(tuple, t.select("user_id", "item_id", "rating", "truth").collect()))
    assert rows(cells) == rows(want) and {r[0] for r in items.collect()} == {r[1] for r in rows(want)}
