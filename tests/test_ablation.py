"""The ablation measures every variant on held cells; noise follows what is protected."""

from locpref.plans import experiment, queries
from locpref.sources.tables import event_visits

KINDS = ("bits", "grads", "both", "none", "central")


def test_ablation_measures_all_variants(spark, small, monkeypatch):
    whole = experiment.sweep
    monkeypatch.setattr(queries, "_AVERAGES", {})
    monkeypatch.setattr(experiment, "sweep", lambda v, grid, **how: whole(v, grid, **(how | {"runs": 10, "rounds": 1})))
    rows = {r.method: r for r in queries.queries()["ablation"](spark, small).collect()}
    assert rows.keys() == set(KINDS)
    for r in rows.values():
        assert r.n == 10 and all(0 <= r[f"{m}_mean"] <= 1 for m in ("fpr", "recall", "reconstruction"))


def test_only_protected_fits_depend_on_eps(spark, small):
    grid = [queries.BASE | {"eps": e} for e in (0.01, 100.0)]
    rows = experiment.sweep(event_visits(spark, small), grid, runs=2, rounds=2, methods=("none", "both")).collect()
    of = lambda m, e: sorted((r.run % 2, r.fpr, r.recall) for r in rows if (r.method, r.eps) == (m, e))
    assert of("none", 0.01) == of("none", 100.0) and of("both", 0.01) != of("both", 100.0)
