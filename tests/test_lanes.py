"""Draws in the JVM are those of the keys."""

import numpy as np
import pytest

from locpref.functions import lanes
from locpref.operators import blocks
from locpref.operators.private import PrivateConfig
from locpref.plans import experiment, queries
from locpref.sources.tables import event_visits


def test_draws_in_the_jvm_equal_those_of_arrays(spark):
    """Keys of one and two blocks, letters of several bytes, runs of one and two digits, a cut repetition, more cells than go through a hash at once."""
    names = ["a@1", "é" * 12 + "@0", "x" * 40, "", "y" * 33]
    method = lambda *protect: PrivateConfig(d=3, rounds=2, seed=7, protect=protect)
    plan = blocks.Plan(((0, 0.5, 1.0), (0, 0.9, 0.01)), (("plain", None, False), ("both", method("bits", "grads"), False), ("grads", method("grads"), False), ("bits", method("bits"), False), ("central", method("bits", "grads"), True)), (0, 1), (names,), 4, 6, 3, 7)
    users, item = np.repeat(np.arange(-3, 297), 4), np.tile([0, 1, 2, 4, 3, 0, 2, 1], 150)
    rows = [(setting, rep, users.tolist(), item.tolist(), [1.0] * 1200, [1] * 1200) for setting in (0, 1) for rep in (0, 1)]
    data = spark.createDataFrame(rows, "setting int, rep int, users array<long>, item array<int>, rating array<double>, truth array<int>")
    for t in (0, 2):
        seen = 0
        for r in lanes.with_draws(data, plan.said(), t).collect():
            cells = (users, item, np.ones(1200), np.ones(1200, int))
            got, want = blocks.Unit(plan, r.setting, r.rep, *cells, r.drawn), blocks.Unit(plan, r.setting, r.rep, *cells)
            assert np.array_equal(got.held, want.held) and np.array_equal(got.first, want.first)
            for m in range(len(plan.methods) if t else 0):
                (w, noise), (w2, each) = (u.drawn(t, *plan.drawn_by(m, r.setting)) for u in (got, want))
                for k in range(plan.of_rep(r.rep)):
                    assert (w[k] is None) == (w2[k] is None) and (w[k] is None or np.array_equal(w[k], w2[k]))
                    assert (noise[k] is None) == (each[k] is None)
                    if noise[k] is not None:
                        share = np.where(want.held[k], 0.0, 1.0 if w2[k] is None else w2[k])
                        assert noise[k] == pytest.approx(np.stack([want.by_item(c * share) for c in each[k]]), rel=1e-9, abs=1e-9)
                        seen += 1
            assert got.drawn_at == len(r.drawn)
        assert seen == (t and 2 * 2 * (4 + 2))


@pytest.mark.parametrize("kind", ["hours", "hourly", "months"])
def test_sweeps_with_and_without_the_jvm_are_equal(spark, small, monkeypatch, kind):
    carrier, how = (queries.order_visits, {"unit": "months"}) if kind == "months" else (event_visits, {"hourly": kind == "hourly"})
    grid = [queries.BASE | {"eps": e} for e in (0.01, 10.0)]
    ask = lambda: {(r.method, r.eps, r.run): (r.fpr, r.recall, r.reconstruction) for r in experiment.sweep(carrier(spark, small), grid, folds=4, runs=6, rounds=2, **how).collect()}
    seen, add = [], lanes.with_draws
    monkeypatch.setattr(lanes, "with_draws", lambda *a: seen.append("drawn" in add(*a).columns) or add(*a))
    got = ask()
    assert seen == [True] * 3
    monkeypatch.setattr(lanes, "with_draws", lambda units, *a: units)
    assert got == ask() and len(got) == 2 * 2 * 6


def test_what_the_text_of_a_plan_cannot_tell_is_drawn_from_arrays(spark):
    plan = blocks.Plan(((0, 0.5, 1.0),), (("plain", None, False),), (0,), (["a\x1fb"],), 4, 6, 3, 7)
    data = spark.createDataFrame([(1,)], "setting int")
    assert plan.said() is None and lanes.with_draws(data, None, 1) is data


def test_few_units_go_to_python_at_once(spark):
    """A unit with the sums of many items is some MB: all units of a task in one batch would not fit."""
    name, make = "spark.sql.execution.arrow.maxRecordsPerBatch", blocks._told
    was = spark.conf.get(name)
    data = spark.createDataFrame([(1, 0, n) for n in range(9)], "setting int, rep int, method int").coalesce(1)

    def work(batches):
        for b in batches:
            yield from make({(1, 0, b.column("method")[0].as_py()): np.array([float(b.num_rows)])}, blocks._SCHEMA)

    got = blocks._summed(data, work)
    assert max(v[0] for v in got.values()) <= blocks.BATCH_UNITS and sum(v[0] for v in got.values()) == 9
    assert spark.conf.get(name) == was
