"""Worked constants, invariants, guarantees, recovery and limits."""

import datetime
import math
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from locpref.functions import granularity as g
from locpref.functions import privacy as pv
from locpref.functions.hashing import gaussian, uniform
from locpref.operators import baselines, dataset, extensions, factorization, metrics, predict, preferences, private, protocol
from locpref.plans import experiment, queries
from locpref.sources import tables

TOY = [(1, 10, 1.0), (1, 20, 0.0), (2, 10, 1.0)]
T3 = "user_id long, item_id long, rating double"


@pytest.fixture(scope="module")
def toy(spark):
    t = spark.createDataFrame(TOY, T3)
    X = spark.createDataFrame([(1, 0.5), (2, 0.8)], "user_id long, x0 double")
    Z = spark.createDataFrame([(10, 0.4), (20, 0.9)], "item_id long, z0 double")
    return t, X, Z


def test_day_keys(spark):
    ts = F.col("ts")
    row = spark.createDataFrame([(datetime.datetime(2019, 2, 1, 14, 0),)], "ts timestamp_ntz").select(g.day_name(ts), g.day_kind(ts), g.day_part(ts), g.month_of(ts), g.time_key(ts, ("month", "name", "part")), *(g.time_slot(ts, w) for w in g.WIDTHS)).first()
    assert tuple(row) == ("Friday", "Weekday", "Afternoon", 2, "2:Friday:Afternoon", *(14 // w for w in g.WIDTHS))
    hours = spark.range(24).select(g.day_part(F.make_timestamp(F.lit(2019), F.lit(2), F.lit(1), F.col("id").cast("int"), F.lit(0), F.lit(0))).alias("p")).collect()
    assert [r.p for r in hours][6:10] == ["Morning"] * 4
    assert [r.p for r in hours][2:6] == ["Midnight"] * 4 and [r.p for r in hours][22:] + [r.p for r in hours][:2] == ["Night"] * 4
    with pytest.raises(ValueError):
        g.time_slot(ts, 5)


def test_grid_cell(spark):
    r = spark.createDataFrame([(-0.1, 10.0), (0.5, -179.9)], "lat double, lon double").select(g.grid_cell(F.col("lat"), F.col("lon"), 0.5).alias("c")).collect()
    assert [tuple(x.c) for x in r] == [(-1, 20), (1, -360)]


def test_rating_rules(spark):
    t0 = datetime.datetime(2020, 1, 1, 1)
    rows = [(1, i, t0 + datetime.timedelta(minutes=i), "a", y) for i, y in enumerate([1, 0, 1])] + [(2, i, t0 + datetime.timedelta(minutes=i), "a", y) for i, y in enumerate([1, 0])] + [(3, 9, None, "a", 1), (4, 9, t0, None, 1)]
    v = spark.createDataFrame(rows, "user_id long, event_id long, ts timestamp_ntz, category string, label int")
    want = {"majority": (1, 0), "latest": (1, 0), "most_private": (0, 0), "most_open": (1, 1)}
    for rule, ratings in want.items():
        got = preferences.build(v, F.col("category"), g.time_slot(F.col("ts"), 6), rule)
        assert {(r.user_id, r.rating) for r in got.collect()} == {(1, ratings[0]), (2, ratings[1])}


def test_four_cells_and_empty_denominators(spark):
    f = lambda rows: metrics.rates(metrics.confusion(spark.createDataFrame(rows, "truth int, decision int"))).first()
    r = f([(1, 1), (0, 1), (1, 0), (0, 0)])
    assert (r.tp, r.fp, r.tn, r.fn, r.fpr, r.recall, r.reconstruction) == (1, 1, 1, 1, 0.5, 0.5, 0.5)
    assert f([(1, 1), (1, 0)]).fpr is None and f([(0, 0)]).recall is None


def test_one_joint_step_by_hand(toy):
    t, X, Z = toy
    cfg = factorization.FitConfig(d=1, norm="ratings", lam_x=0.1, lam_z=0.2)
    res = factorization.residuals(t, X, Z, 1)
    gx = {r.user_id: r.g0 for r in factorization.user_gradient(res, 1, weight=F.lit(1 / 3)).collect()}
    gz = {r.item_id: r.g0 for r in factorization.item_gradient(res, 1, weight=F.lit(1 / 3)).collect()}
    e = {(1, 10): 1 - 0.2, (1, 20): 0 - 0.45, (2, 10): 1 - 0.32}
    assert gx[1] == pytest.approx(-2 / 3 * (0.8 * 0.4 - 0.45 * 0.9))
    assert gz[10] == pytest.approx(-2 / 3 * (e[1, 10] * 0.5 + e[2, 10] * 0.8))
    new = {r.user_id: r.x0 for r in factorization.step(X, factorization.user_gradient(res, 1, weight=F.lit(1 / 3)), "user_id", "x", 0.3, 0.1, cfg).collect()}
    assert new[1] == pytest.approx(0.5 - 0.3 * (gx[1] + 0.2 * 0.5))
    loss = factorization.loss(t, X, Z, cfg).first().loss
    assert loss == pytest.approx(sum(x * x for x in e.values()) / 3 + 0.1 * (0.25 + 0.64) + 0.2 * (0.16 + 0.81))
    assert factorization.loss_dense(t, X, Z, cfg).first()["data"] == pytest.approx(sum(x * x for x in e.values()) / 3)


def test_gradient_is_the_loss_s_slope(toy, spark):
    t, X, Z = toy
    cfg = factorization.FitConfig(d=1, norm="ratings", lam_x=0.1, lam_z=0.2)
    at = lambda x: factorization.loss(t, spark.createDataFrame([(1, x), (2, 0.8)], "user_id long, x0 double"), Z, cfg).first().loss
    slope = (at(0.5 + 1e-5) - at(0.5 - 1e-5)) / 2e-5
    grad = {r.user_id: r.g0 for r in factorization.user_gradient(factorization.residuals(t, X, Z, 1), 1, weight=F.lit(1 / 3)).collect()}
    assert slope == pytest.approx(grad[1] + 2 * 0.1 * 0.5, abs=1e-6)


def test_loss_falls_and_orders_differ_in_the_item_side_first(spark, small):
    t = queries.triples(spark, small)
    m = factorization.fit_plain(t, factorization.FitConfig(d=2, rounds=5, norm="users", trace=True))
    losses = [r["loss"] for r in m.trace]
    assert all(b <= a + 1e-9 for a, b in zip(losses, losses[1:]))
    one = lambda order: factorization.fit_plain(t, factorization.FitConfig(d=2, rounds=1, order=order))
    a, b = one("joint"), one("alternate")
    assert sorted(a.X.collect()) == sorted(b.X.collect()) and sorted(a.Z.collect()) != sorted(b.Z.collect())
    stopped = factorization.fit_plain(t, factorization.FitConfig(d=2, rounds=30, tol=1e-2))
    assert len(stopped.trace) < 30


def test_runs_in_one_plan_equal_single_fits(spark, small):
    t = queries.triples(spark, small)
    cfg = factorization.FitConfig(d=2, rounds=3)
    both = factorization.fit_plain(t.withColumn("run", F.lit(0)).unionByName(t.where("user_id % 2 = 0").withColumn("run", F.lit(1))), cfg, ("run",))
    for run, part in ((0, t), (1, t.where("user_id % 2 = 0"))):
        alone = {r.item_id: (r.z0, r.z1) for r in factorization.fit_plain(part, cfg).Z.collect()}
        rows = both.Z.where(F.col("run") == run).collect()
        assert rows and all(np.allclose(alone[r.item_id], (r.z0, r.z1)) for r in rows)


def test_plain_fit_recovers_a_planted_truth(spark):
    cells = experiment.event_cells(tables.event_visits(spark, "/root/testdata/sf0.01"), 6, hourly=False)
    marked = experiment.repeat(cells, 5, 1, 0.2).where("run = 0")
    known = marked.where("held = 0").select("user_id", "item_id", "rating")
    m = factorization.fit_plain(known, factorization.FitConfig(d=4, rounds=40, norm="users"))
    scored = predict.decide(predict.score(known, m.X, m.Z, 4), predict.mean_threshold(m.X, m.Z, 4))
    right = scored.agg(F.avg((F.col("decision") == F.col("rating")).cast("double"))).first()[0]
    share = known.agg(F.avg("rating")).first()[0]
    assert right > max(share, 1 - share) + 0.12


def test_privacy_closed_forms(spark):
    assert pv.flip_probability(0) == 1 and pv.flip_probability(1e4) == 0
    for eps in (0.01, 0.5, 2.0, 10.0):
        p = pv.flip_probability(eps)
        assert (2 - p) / p == pytest.approx(math.exp(eps), rel=1e-12)
    for r in pv.audit(spark, [0.1, 1.0, 3.0]).collect():
        assert r.bit_ratio == pytest.approx(1) and r.laplace_ratio <= 1 + 1e-12
    with pytest.raises(ValueError):
        pv.Budget("per_report", 0.0)
    with pytest.raises(ValueError):
        pv.bit_weight(F.lit(1), 1.0)


def test_clip(spark):
    v = spark.createDataFrame([(3.0, -4.0), (0.1, 0.1), (0.0, 0.0)], "a double, b double")
    for kind, n in (("l1", lambda a, b: abs(a) + abs(b)), ("l2", math.hypot), ("coordinate", lambda a, b: max(abs(a), abs(b)))):
        once = pv.clip([F.col("a"), F.col("b")], 1.0, kind)
        rows = v.select(*(c.alias(n_) for c, n_ in zip(once, "ab"))).collect()
        assert all(n(r.a, r.b) <= 1 + 1e-12 for r in rows) and (rows[1].a, rows[1].b) == (0.1, 0.1)


def test_budget_policies_and_ledger(spark):
    assert pv.Budget("per_report", 1.0, 0.25, 10, 5).per_round() == (0.25, 0.75)
    assert pv.Budget("per_item", 1.0, 0.5, 10, 5).per_round() == (0.05, 0.05)
    assert pv.Budget("per_user", 1.0, 0.5, 10, 5).per_round() == (0.01, 0.01)
    assert pv.Budget("per_item", 1.0, 0.5, 10, 5, True).per_round() == (0.5, 0.05)
    users = spark.range(2).withColumnRenamed("id", "user_id")
    for policy in ("per_item", "per_user"):
        for permanent in (False, True):
            assert pv.ledger(users, pv.Budget(policy, 1.0, 0.3, 6, 4, permanent)).agg(F.max("eps_total")).first()[0] == pytest.approx(1.0)


def test_bits_are_unbiased_stable_and_permanent(spark):
    cells = spark.range(40_000).select((F.col("id") % 400).alias("user_id"), F.floor(F.col("id") / 400).alias("item_id"), (F.col("id") % 5 == 0).cast("int").alias("y"))
    p = pv.flip_probability(1.0)
    for n in (1, 7, 64):
        b = private.noisy_bits(cells.repartition(n), p, 42, 1)
        got = b.agg(F.avg(pv.bit_weight(F.col("ybit"), p)), F.bit_xor(F.xxhash64("user_id", "item_id", "ybit"))).first()
        assert abs(got[0] - 0.2) < 4 * math.sqrt(math.e) / (math.e - 1) / 200
        assert n == 1 or got[1] == seen
        seen = got[1]
    same = [private.noisy_bits(cells, p, 42, t, "permanent").agg(F.sum(F.col("ybit") * F.col("user_id"))).first()[0] for t in (1, 2)]
    fresh = [private.noisy_bits(cells, p, 42, t).agg(F.sum(F.col("ybit") * F.col("user_id"))).first()[0] for t in (1, 2)]
    assert same[0] == same[1] and fresh[0] != fresh[1]


def test_reports_hold_no_clear_value(spark, small):
    t, X, Z = queries.start(spark, small)
    r = protocol.Round(queries.PRIVATE)
    out = r.client(t, X, r.publish(X, Z)[1])
    assert set(out.columns) == {"item_id", "ybit", "g0", "g1"} and r.publish(X, Z)[0] is None
    assert out.count() == X.count() * Z.count()


def test_no_noise_is_the_plain_fit(spark, small):
    t = queries.triples(spark, small)
    big = private.PrivateConfig(d=2, rounds=4, eps=1e6, clip=100.0, lam_x=1e-4, lam_z=1e-4)
    bare = replace(big, protect=())
    plain = factorization.fit_plain(t, factorization.FitConfig(d=2, rounds=4, norm="users", max_norm=2.0))
    want = {r.item_id: (r.z0, r.z1) for r in plain.Z.collect()}
    for cfg, tol in ((bare, 1e-9), (big, 1e-2)):
        got = {r.item_id: (r.z0, r.z1) for r in private.fit_private(t, cfg).Z.collect()}
        assert max(abs(a - b) for k in want for a, b in zip(want[k], got[k])) < tol


def test_synthesised_noise_has_the_reports_spread(spark):
    n, p, scale = 60, pv.flip_probability(1.0), 3.0
    items = spark.range(4000).select(F.col("id").alias("item_id"), F.lit(10).alias("rated"), F.lit(n).alias("n"), F.lit(p).alias("p"), F.lit(scale).alias("scale"))
    fast = private.synthesize_noise(items, 1, 1, 1).agg(F.avg("s0"), F.stddev("s0")).first()
    e = math.e
    want = math.sqrt((n - 10) * e / (e - 1) ** 2 * 2 * scale**2)
    assert abs(fast[0]) < 4 * want / math.sqrt(4000) and fast[1] == pytest.approx(want, rel=0.08)
    cells = spark.range(50 * 800).select((F.col("id") % 50).alias("user_id"), F.floor(F.col("id") / 50).alias("item_id"), F.lit(0).alias("y"))
    w = pv.bit_weight(F.col("ybit"), p) * pv.laplace(uniform(7, "l", F.col("user_id"), F.col("item_id")), scale)
    slow = private.noisy_bits(cells, p, 3).groupBy("item_id").agg(F.sum(w).alias("s")).agg(F.stddev("s")).first()[0]
    assert slow == pytest.approx(want, rel=0.12)


def test_secure_noise_differs_and_has_the_scale(spark):
    a = spark.range(20_000).select(pv.laplace_secure(2.0, F.col("id")).alias("x"))
    s = a.agg(F.avg(F.abs("x"))).first()[0]
    assert abs(s - 2.0) < 0.1


def test_secure_mode_leaves_nothing_to_the_seed(spark, small):
    """Bits, samples and noise of two runs with one seed differ; permanent bits are drawn once and kept."""
    t, X, Z = queries.start(spark, small)
    for kind in ({}, {"report_sample": 5}, {"bit_mode": "permanent"}):
        cfg = replace(queries.PRIVATE, noise="secure", **kind)
        sent = [private.client_reports(X, t, Z, cfg, 1, 0.9, 1.0).select("user_id", "item_id", "ybit", "g0", "g1").collect() for _ in range(2)]
        bits = [{(r.user_id, r.item_id): r.ybit for r in x} for x in sent]
        assert bits[0] != bits[1]
        assert ("report_sample" not in kind) or bits[0].keys() != bits[1].keys()
        assert not {r.g0 for r in sent[0]} & {r.g0 for r in sent[1]}
        assert len({r.g0 - r.g1 for r in sent[0]}) > 1  # a draw for each coordinate
    seen = []
    kept = private.client_reports
    for kind in ({"bit_mode": "permanent"}, {"bit_mode": "permanent", "report_sample": 5}):
        cfg = replace(queries.PRIVATE, noise="secure", rounds=2, **kind)
        try:
            private.client_reports = lambda *a, **k: seen.append(sorted(map(tuple, a[7].collect()))) or kept(*a, **k)
            private.fit_private(t, cfg)
        finally:
            private.client_reports = kept
    assert seen[0] == seen[1] and seen[2] == seen[3] and seen[0] != seen[2]
    one = [sorted(map(tuple, private.fit_private(t, replace(cfg, user_side="server", rounds=1)).X.collect())) for _ in range(2)]
    assert one[0] != one[1]


def test_a_sample_has_exactly_its_size(spark, small):
    t, X, Z = queries.start(spark, small)
    m = Z.count()
    for s, rounds in ((1, (1, 2)), (7, (1, 2, 3)), (m + 5, (1,))):
        cfg = replace(queries.PRIVATE, report_sample=s, policy="per_user", rounds=len(rounds))
        chosen = []
        for r in rounds:
            cells = private.sampled_cells(X, Z.select("item_id"), cfg, r)
            counts = {x.user_id: (x.n, x.d) for x in cells.groupBy("user_id").agg(F.count("*").alias("n"), F.countDistinct("item_id").alias("d")).collect()}
            assert set(counts.values()) == {(min(s, m), min(s, m))} and len(counts) == X.count()
            chosen.append(frozenset(map(tuple, cells.collect())))
        assert len(set(chosen)) == len(rounds)
        assert cfg.budget(m).items == min(s, m)
    perm = replace(queries.PRIVATE, report_sample=4, bit_mode="permanent")
    assert sorted(private.sampled_cells(X, Z.select("item_id"), perm, 1).collect()) == sorted(private.sampled_cells(X, Z.select("item_id"), perm, 2).collect())
    wide = spark.range(4000).select(F.col("id").alias("user_id"))
    by_item = private.sampled_cells(wide, Z.select("item_id"), replace(queries.PRIVATE, report_sample=5), 1).groupBy("item_id").count().collect()
    assert len(by_item) == m and all(abs(r["count"] - 4000 * 5 / m) < 6 * math.sqrt(4000 * 5 / m) for r in by_item)


def test_three_releases_share_the_budget(spark):
    users = spark.range(2).withColumnRenamed("id", "user_id")
    for policy in ("per_item", "per_user"):
        for permanent in (False, True):
            b = pv.Budget(policy, 1.0, 0.3, 6, 4, permanent, 0.25)
            rows = pv.ledger(users, b)
            assert rows.agg(F.max("eps_total")).first()[0] == pytest.approx(1.0)
            assert {r.mechanism for r in rows.collect()} == {"bit", "gradient", "user_gradient"}
    server = private.PrivateConfig(d=2, rounds=3, eps=2.0, user_side="server", policy="per_user")
    bit, grad = server.budget(10).per_round()
    assert 3 * (10 * (bit + grad) + server.budget(10).user_gradient()) == pytest.approx(2.0)
    assert server.user_scale(10) == pytest.approx(2 * server.clip / server.budget(10).user_gradient())
    assert private.PrivateConfig(user_side="client").budget(10).user_share == 0.0


def test_rounds_by_user_meet_without_a_shuffle(spark, small):
    from locpref.sources.rounds import Rounds

    t = queries.triples(spark, small)
    scratch = Rounds(spark, "layout")
    data = scratch.keep(t, "triples", ["user_id"])
    X = scratch.keep(factorization.init_factors(t.select("user_id").distinct(), "user_id", "x", 2), "x", ["user_id"])
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = data.join(X, "user_id").groupBy("user_id").agg(F.sum("x0"))._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    assert "SortMergeJoin" in plan and "Exchange" not in plan
    scratch.drop("triples", "x")


def test_unknown_cells_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(preferences, "ITEM_BLOCK", 7)
    t = spark.range(200).selectExpr("id % 10 AS user_id", "id * 7 % 40 AS item_id")
    got = {tuple(r) for r in preferences.unknown_cells(t.select("user_id"), t, t, "item_id").collect()}
    known = {tuple(r) for r in t.collect()}
    assert got == {(u, i) for u in range(10) for i in {k for _, k in known}} - known


def test_gaussian_draws(spark):
    r = spark.range(20_000).select(gaussian(1, "g", F.col("id")).alias("x")).agg(F.avg("x"), F.stddev("x")).first()
    assert abs(r[0]) < 0.03 and abs(r[1] - 1) < 0.03


def test_masks_and_folds(spark, small):
    t = queries.triples(spark, small)
    folds = experiment.user_folds(t)
    assert folds.groupBy("user_id").count().where("count > 1").isEmpty()
    test = folds.where("fold < 3")
    m = experiment.mask_unknown(t, test, 0.4)
    assert m.where("held = 1").join(test, "user_id", "left_anti").isEmpty()
    assert m.count() == t.count()
    assert experiment.mask_unknown(t, test, 0.0).where("held = 1").isEmpty()
    assert experiment.mask_unknown(t, test, 1.0).where("held = 0").join(test, "user_id", "left_semi").isEmpty()
    runs = experiment.repeat(t, 4, 2, 0.5)
    assert runs.count() == 8 * t.count()
    tested = runs.where("held = 1").select(F.floor(F.col("run") / 4).alias("rep"), "run", "user_id").distinct().groupBy("rep", "user_id").count()
    assert tested.where("count > 1").isEmpty()


def test_thresholds_and_ties(spark, toy):
    t, X, Z = toy
    grid = np.outer([0.5, 0.8], [0.4, 0.9])
    assert predict.mean_threshold(X, Z, 1).first().threshold == pytest.approx(grid.mean())
    assert {r.user_id: r.threshold for r in predict.mean_threshold(X, Z, 1, scope="per_user").collect()} == pytest.approx({1: 0.325, 2: 0.52})
    assert predict.mean_threshold(X, Z, 1, scope="fixed").first().threshold == 0.5
    scored = spark.createDataFrame([(1, 10, 0.5), (1, 20, 0.6)], "user_id long, item_id long, score double")
    assert [r.decision for r in predict.decide(scored, predict.mean_threshold(X, Z, 1, scope="fixed")).orderBy("item_id").collect()] == [0, 1]


def test_fold_in(spark, toy):
    t, _, Z = toy
    x = {r.user_id: r.x0 for r in factorization.fold_in(t, Z, 1, lam=0.1).collect()}
    assert x[1] == pytest.approx(0.4 / (0.16 + 0.81 + 0.2))
    gd = {r.user_id: r.x0 for r in factorization.fold_in(t, Z, 1, lam=0.1, method="gd", rounds=400).collect()}
    assert gd[1] == pytest.approx(x[1], rel=1e-3)
    assert factorization.fold_in(t.limit(0), Z, 1).count() == 0


def test_constants_and_coin(spark):
    cells = spark.createDataFrame([(1, 1, 1), (1, 2, 0), (2, 1, 1)], "user_id long, item_id long, truth int")
    for d in (0, 1):
        r = metrics.rates(metrics.confusion(baselines.constant(cells, d)), "fpr", "recall").first()
        assert (r.fpr, r.recall) == (d, d)


def test_dense_ids_agree(spark, small):
    t = queries.triples(spark, small)
    a, b = (sorted(preferences.index(t, "item_id", k).collect()) for k in ("rank", "range"))
    assert a == b and [r.id for r in a] == list(range(len(a)))


def test_temporal_leakage():
    assert extensions.temporal_leakage([0.5] * 3) == [0.5, 1.0, 1.5]
    flat = extensions.temporal_leakage([0.5] * 3, [[0.5, 0.5], [0.5, 0.5]])
    assert flat == pytest.approx([0.5] * 3)
    sure = extensions.temporal_leakage([0.5] * 3, [[1.0, 0.0], [0.0, 1.0]])
    assert sure == pytest.approx([0.5, 1.0, 1.5])


def test_sweep_rows_share_masks(spark, small):
    v = tables.event_visits(spark, small)
    rows = experiment.sweep(v, [{"width": 6, "eps": 10.0, "unknown": 0.5}, {"width": 12, "eps": 0.01, "unknown": 0.5}], folds=3, runs=2, rounds=2).collect()
    assert len(rows) == 8 and {r.method for r in rows} == {"plain", "private"} and {(r.width, r.eps) for r in rows} == {(6, 10.0), (12, 0.01)}
    assert all(0 <= r.reconstruction <= 1 for r in rows if r.reconstruction is not None)


def test_archetype_labels_and_integration(spark, small):
    survey, visits = queries.survey_and_visits(spark, small)
    for mode in ("rate", "archetype", "hybrid"):
        out = dataset.integrate(survey, visits, mode)
        assert out.count() == visits.count()
        assert mode == "archetype" or out.where("label is null").isEmpty()


def test_model_store_and_formats(spark, small, tmp_path):
    t, X, Z = queries.start(spark, small)
    tables.save_model(X, Z, {"d": 2}, f"{tmp_path}/m")
    x, z, cfg = tables.load_model(spark, f"{tmp_path}/m")
    assert cfg == {"d": 2} and x.count() == X.count() and z.count() == Z.count()
    own = t.withColumn("item_id", F.xxhash64("item_id")).select("user_id", "item_id", "rating")
    for kind in ("parquet", "orc", "json", "csv"):
        tables.write_triples(own, f"{tmp_path}/{kind}", kind)
        assert sorted(tables.read_triples(spark, f"{tmp_path}/{kind}", kind).collect()) == sorted(own.collect())


def test_no_grid_in_plans(spark, small):
    t, X, Z = queries.start(spark, small)
    plan = predict.mean_threshold(X, Z, 2)._jdf.queryExecution().executedPlan().toString()
    res = factorization.item_gradient(factorization.residuals(t, X, Z, 2), 2)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "CartesianProduct" not in res and "NestedLoop" not in res
