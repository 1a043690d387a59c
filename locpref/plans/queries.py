"""Registered queries: the methods on the given tables. Floating results are rounded for comparison."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import granularity as g
from ..functions import privacy as pv
from ..functions.hashing import uniform
from ..operators import baselines, dataset, extensions, factorization, metrics, predict, preferences, private, protocol
from ..sources.rounds import Rounds, shared_root
from ..sources.tables import event_visits, order_visits, survey_answers, table
from ..streaming import checkins
from . import experiment

SEED, D, WIDTH = 42, 2, 6
PLAIN = factorization.FitConfig(d=D, rounds=3, norm="ratings")
PRIVATE = private.PrivateConfig(d=D, rounds=2, eps=2.0)
#: Folds of the cross validation over users, and repetitions of the whole of it: in queries on the small carrier, and on the large one.
#: ``bench.py`` has one with a hundred.
FOLDS, REPEATS, REPEATS_LARGE = 10, 10, 1
BASE = {"eps": 0.01, "unknown": 0.1, "width": 6}
Query = Callable[[SparkSession, str], DataFrame]


def r6(*names: str) -> dict[str, Column]:
    return {n: F.round(F.col(n), 6) for n in names}


def slot(hours: int = WIDTH) -> Column:
    return g.time_slot(F.col("ts"), hours)


def triples(spark: SparkSession, d: str, hours: int = WIDTH, rule: str = "majority") -> DataFrame:
    """``user_id, item_id, rating`` of events by category and slot."""
    return preferences.build(event_visits(spark, d), F.col("category"), slot(hours), rule).select("user_id", F.col("item").alias("item_id"), "rating")


def start(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    t = triples(spark, d)
    return t, factorization.init_factors(t.select("user_id").distinct(), "user_id", "x", D), factorization.init_factors(t.select("item_id").distinct(), "item_id", "z", D)


def planted_cells(spark: SparkSession, d: str) -> DataFrame:
    t = triples(spark, d).select("user_id", F.col("item_id").alias("item"))
    return dataset.planted(t).select("user_id", F.col("item").alias("item_id"), "truth", "rating")


def stats_of(cells: DataFrame) -> DataFrame:
    return preferences.matrix_stats(cells).withColumns(r6("density", "positive"))


def slots(hours: int) -> Query:
    return lambda s, d: stats_of(preferences.build(event_visits(s, d), F.col("category"), slot(hours)))


def counted(**keys: Callable[[Column], Column]) -> Query:
    """Events by keys made from their time."""
    return lambda s, d: event_visits(s, d).groupBy(*(make(F.col("ts")).alias(n) for n, make in keys.items())).agg(F.count("*").alias("n"))


def calendar_slots(s, d):
    return event_visits(s, d).groupBy(g.calendar_slot(F.col("ts"), WIDTH).alias("t")).agg(F.count("*").alias("n")).select(F.date_format("t", "yyyy-MM-dd HH:mm").alias("slot_start"), "n")


def month_slots(s, d):
    o = table(s, d, "orders")
    return o.groupBy(g.month_slot(F.col("o_orderdate"), 3).alias("slot")).agg(F.count("*").alias("n"), F.countDistinct("o_custkey").alias("users"))


def location_ladder(s, d):
    return g.rollup_location(order_visits(s, d), ("region", "area"))


def location_keys(kind: str) -> Query:
    def run(s, d):
        visits = event_visits(s, d) if kind in ("category", "category_place") else order_visits(s, d)
        return visits.groupBy(g.location_key(kind).alias("loc")).agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("users"))

    return run


def prefs(rule: str) -> Query:
    return lambda s, d: preferences.build(event_visits(s, d), F.col("category"), slot(), rule)


def prefs_supported(s, d):
    return preferences.build(event_visits(s, d), F.col("category"), slot(), "majority", 3)


def matrix_stats_events(s, d):
    return stats_of(preferences.build(event_visits(s, d), g.location_key("category_place"), slot()))


def matrix_stats_lineitem(s, d):
    return stats_of(preferences.build(order_visits(s, d), F.col("area"), g.month_slot(F.col("ts"), 6)))


def degree_quantiles(s, d):
    return preferences.degrees(triples(s, d), "user_id").agg(*(F.expr(f"percentile(degree, {q})").alias(f"q{int(100 * q)}") for q in (0.1, 0.5, 0.9)))


def dense_ids(method: str) -> Query:
    return lambda s, d: preferences.index(triples(s, d), "item_id", method)


def survey_and_visits(s, d):
    visits = event_visits(s, d).withColumn("slot", slot())
    return dataset.mapped_survey(survey_answers(s, d), visits), visits


def survey_rates(s, d):
    return dataset.survey_rates(survey_and_visits(s, d)[0]).withColumns(r6("rate"))


def transferred(mode: str) -> Query:
    def run(s, d):
        out = dataset.integrate(*survey_and_visits(s, d), mode)
        return out.groupBy("category", "slot").agg(F.count("*").alias("n"), F.count("label").alias("labelled"), F.sum("label").cast("long").alias("open"))

    return run


def archetypes_cosine(s, d):
    survey, visits = survey_and_visits(s, d)
    return dataset.archetypes(survey, visits, "cosine").groupBy("respondent").agg(F.count("*").alias("users"))


def described(carrier) -> Query:
    return lambda s, d: dataset.describe(carrier(s, d)).withColumns({c: F.date_format(c, "yyyy-MM-dd") for c in ("first_ts", "last_ts")})


def user_folds(s, d):
    return experiment.user_folds(event_visits(s, d))


def user_folds_exact(s, d):
    return experiment.user_folds(event_visits(s, d), exact=True).groupBy("fold").agg(F.count("*").alias("users"))


def masked_cells(h: int) -> Query:
    def run(s, d):
        t = triples(s, d)
        return experiment.mask_unknown(t, experiment.user_folds(t).where("fold = 0"), h / 10)

    return run


def init_factors(s, d):
    _, X, _ = start(s, d)
    return X.withColumns(r6("x0", "x1"))


def score_cells(s, d):
    t, X, Z = start(s, d)
    return predict.score(t, X, Z, D).withColumns(r6("score"))


def loss_initial(s, d):
    return factorization.loss(*start(s, d), PLAIN).withColumns(r6("loss"))


def loss_dense(s, d):
    t, X, Z = start(s, d)
    sparse = factorization.residuals(t, X, Z, D).agg(F.avg(F.col("e") * F.col("e")).alias("sparse"))
    return factorization.loss_dense(t, X, Z, PLAIN).withColumnRenamed("data", "dense").crossJoin(sparse).withColumns(r6("dense", "sparse"))


def user_gradient(s, d):
    t, X, Z = start(s, d)
    return factorization.user_gradient(factorization.residuals(t, X, Z, D), D).withColumns(r6("g0", "g1"))


def item_gradient(s, d):
    t, X, Z = start(s, d)
    return factorization.item_gradient(factorization.residuals(t, X, Z, D), D).withColumns(r6("g0", "g1"))


def fitted(**changes) -> Query:
    from dataclasses import replace

    return lambda s, d: factorization.fit_plain(triples(s, d), replace(PLAIN, **changes)).Z.withColumns(r6("z0", "z1"))


def fit_trace(s, d):
    m = factorization.fit_plain(triples(s, d), factorization.FitConfig(d=D, rounds=4, trace=True, step=factorization.StepSize("bold", 0.5)))
    return s.createDataFrame([(r["round"], r["loss"], r["gamma"]) for r in m.trace], "round int, loss double, gamma double").withColumns(r6("loss", "gamma"))


def mean_threshold(scope: str) -> Query:
    def run(s, d):
        t, X, Z = start(s, d)
        return predict.mean_threshold(X, Z, D, scope=scope, observed=t).withColumns(r6("threshold"))

    return run


def mean_threshold_grid(s, d):
    _, X, Z = start(s, d)
    return X.crossJoin(Z).agg(F.avg(factorization.dot(D)).alias("threshold")).withColumns(r6("threshold"))


def unknown_cells(s, d):
    t = triples(s, d)
    return preferences.unknown_cells(t.select("user_id"), t, t, "item_id")


def fitted_model(s, d):
    t = triples(s, d)
    m = factorization.fit_plain(t, PLAIN)
    return t, m.X, m.Z


def recommend(s, d):
    t, X, Z = fitted_model(s, d)
    cells = preferences.unknown_cells(t.select("user_id"), t, t, "item_id")
    return predict.recommend(cells, X, Z, D).withColumns(r6("score"))


def top_k(s, d):
    """The three best unrated cells of every user."""
    t, X, Z = fitted_model(s, d)
    cells = preferences.unknown_cells(t.select("user_id"), t, t, "item_id")
    scored = predict.score(cells, X, Z, D).withColumn("score", F.round("score", 6))
    return predict.top_k(scored, 3).select("user_id", "item_id", "rank", "score")


def customer_levels(s, d):
    """``eps, users``: levels that customers can afford, a hundredth for ten of their balance."""
    eps = F.floor(F.abs(F.col("c_acctbal")) / 10) / 100
    return table(s, d, "customer").where("c_acctbal is not null").groupBy(eps.cast("double").alias("eps")).agg(F.count("*").alias("users"))


def flip_probability_grid(s, d):
    """The flip probability at every level of the customers."""
    return customer_levels(s, d).select("eps", F.round(pv.flip_probability_column(F.col("eps")), 9).alias("p"), "users")


def bit_cells(s, d):
    t = triples(s, d)
    grid = t.select("user_id").distinct().crossJoin(t.select("item_id").distinct())
    return grid.join(t, ["user_id", "item_id"], "left").select("user_id", "item_id", F.col("rating").isNotNull().cast("int").alias("y"))


def noisy_bits(mode: str) -> Query:
    return lambda s, d: private.noisy_bits(bit_cells(s, d), pv.flip_probability(1.0), SEED, 1, mode)


def visit_estimates(s, d):
    p = pv.flip_probability(1.0)
    bits = private.noisy_bits(bit_cells(s, d), p, SEED, 1)
    return private.estimate_visits(bits, p).join(bits.groupBy("item_id").agg(F.avg("y").alias("truth")), "item_id").withColumns(r6("estimate", "truth"))


def bits_by_user(s, d):
    """Every user with a level of their own, by market segment."""
    eps = table(s, d, "customer").select(F.col("c_custkey").alias("user_id"), (1.0 + F.length("c_mktsegment") / 10).alias("eps"))
    cells = bit_cells(s, d).join(eps, "user_id").withColumn("p", pv.flip_probability_column(F.col("eps")))
    bits = private.noisy_bits(cells, F.col("p"), SEED, 1)
    return bits.groupBy("item_id").agg(F.round(F.avg(pv.bit_weight(F.col("ybit"), F.col("p"))), 6).alias("estimate"), F.count("*").alias("n"))


def laplace_noise(s, d):
    return event_visits(s, d).select("event_id", F.round(pv.laplace(uniform(SEED, "lap", F.col("event_id")), 2.0), 6).alias("noise"))


def clipped_gradients(kind: str) -> Query:
    from dataclasses import replace

    def run(s, d):
        t, X, Z = start(s, d)
        return private.clipped_gradients(factorization.residuals(t, X, Z, D), replace(PRIVATE, clip=0.2, clip_norm=kind)).withColumns(r6("g0", "g1"))

    return run


def reports(kind: str) -> DataFrame:
    from dataclasses import replace

    def run(s, d):
        t, X, Z = start(s, d)
        cfg = replace(PRIVATE, report=kind)
        p, scale = cfg.mechanism(Z.count())
        return private.client_reports(X, t, Z, cfg, 1, p, scale), cfg, p

    return run


def client_reports(s, d):
    return reports("pair")(s, d)[0].withColumns(r6("g0", "g1"))


def aggregated(kind: str) -> Query:
    def run(s, d):
        return private.aggregate_reports(*reports(kind)(s, d)).withColumns(r6("g0", "g1"))

    return run


def fit_private(mode: str = "reports", **changes) -> Query:
    from dataclasses import replace

    def run(s, d):
        t = triples(s, d)
        return private.fit_private(t, replace(PRIVATE, **changes), mode).Z.withColumns(r6("z0", "z1"))

    return run


def synthesized_noise(s, d):
    t = triples(s, d)
    items = t.groupBy("item_id").agg(F.count("*").alias("rated")).crossJoin(t.agg(F.countDistinct("user_id").alias("n")))
    p, scale = PRIVATE.mechanism(1)
    return private.synthesize_noise(items.withColumns({"p": F.lit(p), "scale": F.lit(scale)}), D, SEED, 1).withColumns(r6("s0", "s1"))


def protocol_round(s, d):
    t, X, Z = start(s, d)
    r = protocol.Round(PLAIN)
    return r.server(r.client(t, *r.publish(X, Z)), X, Z)[1].withColumns(r6("z0", "z1"))


def budget_ledger(s, d):
    users = table(s, d, "customer").select(F.col("c_custkey").alias("user_id"))
    return pv.ledger(users, pv.Budget("per_item", 1.0, 0.5, rounds=4)).withColumns(r6("eps_spent", "eps_total"))


def budget_ledger_server(s, d):
    """The ledger with the third release, user gradients on the server's side."""
    users = table(s, d, "customer").select(F.col("c_custkey").alias("user_id"))
    return pv.ledger(users, pv.Budget("per_user", 1.0, 0.5, rounds=4, items=5, user_share=0.25)).withColumns(r6("eps_spent", "eps_total"))


def ledger_totals(s, d):
    """What customers have spent at the end, at most, under every policy that bounds it, by kind of bits and side of the user step."""
    users = table(s, d, "customer").select(F.col("c_custkey").alias("user_id"))
    out = None
    for policy in ("per_item", "per_user"):
        for permanent in (False, True):
            for share in (0.0, 0.25):
                spent = pv.totals(users, pv.Budget(policy, 1.0, 0.5, 6, 4, permanent, share))
                row = spent.agg(F.round(F.max("eps_total"), 6).alias("eps_total"), F.max("releases").alias("releases"), F.count("*").alias("users")).select(F.lit(policy).alias("policy"), F.lit(permanent).alias("permanent"), F.lit(share).alias("user_share"), "eps_total", "releases", "users")
                out = row if out is None else out.unionByName(row)
    return out


def private_round(s, d):
    """A round of the private protocol: item factors out, noisy reports back, a step from reports alone."""
    t, X, Z = start(s, d)
    r = protocol.Round(PRIVATE)
    return r.server(r.client(t, X, r.publish(X, Z)[1]), X, Z)[1].withColumns(r6("z0", "z1"))


def sampled_reports(s, d):
    """How many items each user reports: exactly the sample, chosen without the data."""
    from dataclasses import replace

    t, X, Z = start(s, d)
    cfg = replace(PRIVATE, report_sample=5)
    sent = private.client_reports(X, t, Z, cfg, 1, *cfg.mechanism(Z.count()))
    return sent.groupBy("user_id").agg(F.count("*").alias("reports"), F.countDistinct("item_id").alias("items"))


def aggregated_by_levels(s, d):
    """Mean gradients from users with levels of their own, by market segment."""
    t, X, Z = start(s, d)
    eps = table(s, d, "customer").select(F.col("c_custkey").alias("user_id"), (1.0 + F.length("c_mktsegment") / 10).alias("eps"))
    sent = private.client_reports(X, t, Z, PRIVATE, 1, 0.0, 0.0, levels=eps)
    return private.aggregate_reports(sent, PRIVATE, 0.0, F.col("w")).withColumns(r6("g0", "g1"))


def observed_traffic(s, d):
    """Numbers and bytes that the reports of one round hold, counted on the reports themselves."""
    out = None
    for kind in ("pair", "product"):
        sent = reports(kind)(s, d)[0]
        width = 8 * D + (1 if kind == "pair" else 0)
        row = sent.agg(F.count("*").alias("reports"), F.countDistinct("user_id").alias("users"), F.countDistinct("item_id").alias("items")).select(F.lit(kind).alias("kind"), "reports", "users", "items", (F.col("reports") * width).alias("bytes_up"))
        out = row if out is None else out.unionByName(row)
    return out


def factor_norms(s, d):
    """Sizes of both sides' vectors after a fit."""
    _, X, Z = fitted_model(s, d)
    size = lambda f, p, side: f.select(F.sqrt(sum((F.col(c) * F.col(c) for c in factorization.cols(p, D)), F.lit(0.0))).alias("x")).agg(F.round(F.min("x"), 6).alias("least"), F.round(F.avg("x"), 6).alias("mean"), F.round(F.max("x"), 6).alias("most"), F.count("*").alias("n")).select(F.lit(side).alias("side"), "*")
    return size(X, "x", "user").unionByName(size(Z, "z", "item"))


def fold_in_descent(s, d):
    t, _, Z = fitted_model(s, d)
    return factorization.fold_in(t, Z, D, method="gd", rounds=2).withColumns(r6("x0", "x1"))


def privacy_audit(s, d):
    """Worst likelihood ratios at every level of the customers."""
    return pv.audit_levels(customer_levels(s, d).where("eps > 0").select("eps")).withColumns(r6("bit_ratio", "laplace_ratio"))


def fold_in(s, d):
    t, _, Z = fitted_model(s, d)
    return factorization.fold_in(t, Z, D).withColumns(r6("x0", "x1"))


def als_baseline(s, d):
    t = preferences.build(event_visits(s, d), F.col("category"), slot()).select("user_id", "item", "rating")
    ids = preferences.index(t, "item", "rank")
    cells = t.join(ids, "item").select("user_id", F.col("id").alias("item_id"), "rating")
    return baselines.als(cells, cells.select("user_id", "item_id"))


def cf(side: str, sim: str = "cosine") -> Query:
    def run(s, d):
        t = triples(s, d)
        asked = t.select("user_id", "item_id")
        return (baselines.cf_user if side == "user" else baselines.cf_item)(asked, t, 5, sim).withColumns(r6("score"))

    return run


def majority(by: str) -> Query:
    def run(s, d):
        t = triples(s, d)
        return baselines.majority(t.select("user_id", "item_id"), t, by).withColumns(r6("score"))

    return run


def constant(decision: int) -> Query:
    def run(s, d):
        cells = baselines.constant(planted_cells(s, d), decision)
        return metrics.rates(metrics.confusion(cells), "fpr", "recall")

    return run


def coin(s, d):
    return metrics.confusion(baselines.coin(planted_cells(s, d), 0.5))


def k_anonymous(s, d):
    visits = event_visits(s, d).withColumn("item", preferences.item_key(F.col("place"), slot()))
    return baselines.k_anonymous(visits, 20).groupBy("item").agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("users"))


def coarsened(s, d):
    levels = table(s, d, "customer").select(F.col("c_custkey").alias("user_id"), F.when(F.col("c_mktsegment") == "BUILDING", 0).when(F.col("c_mktsegment") == "MACHINERY", 1).otherwise(2).alias("level"))
    return baselines.coarsen(order_visits(s, d), levels).groupBy("level").agg(F.count("*").alias("n"), F.countDistinct("shown").alias("shown"))


def scored_planted(s, d):
    cells = planted_cells(s, d)
    m = baselines.majority(cells, cells.select("user_id", "item_id", "rating"), "item").withColumn("score", F.round("score", 9))
    marked = experiment.mask_unknown(m, experiment.user_folds(m).where("fold = 0"), 0.3)
    return marked.withColumn("decision", (F.col("score") > 0.6).cast("int"))


def confusion(s, d):
    return metrics.confusion(scored_planted(s, d))


def fpr_recall(s, d):
    return metrics.rates(metrics.confusion(scored_planted(s, d))).withColumns(r6("fpr", "recall", "reconstruction", "precision", "f1", "balanced"))


def reconstruction(s, d):
    return metrics.rates(metrics.confusion(scored_planted(s, d).where("held = 1")), "reconstruction").withColumns(r6("reconstruction"))


def rmse(s, d):
    return metrics.closeness(scored_planted(s, d)).withColumns(r6("rmse", "mae"))


def metrics_cube(s, d):
    cells = scored_planted(s, d).withColumn("slot", F.substring_index("item_id", "@", -1))
    return cells.cube("slot", "held").agg(F.grouping_id().cast("long").alias("level"), F.count("*").alias("n"), F.count_if(F.col("decision") == F.col("truth")).alias("right"))


def traffic(s, d):
    """Bytes of 50 rounds at rank 8, for the users, items and ratings of the events."""
    n = triples(s, d).agg(F.countDistinct("user_id").alias("users"), F.countDistinct("item_id").alias("items"), F.count("*").alias("ratings")).first()
    return metrics.traffic(s, n.users, n.items, 8, n.ratings, 50)


def planted_triples(s, d):
    return planted_cells(s, d)


def asof_preference(s, d):
    """The last label of the user's even-numbered events before each odd-numbered one."""
    v = event_visits(s, d)
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    stated = F.when(F.col("event_id") % 2 == 0, F.col("label"))
    return v.withColumn("stated", F.last(stated, ignorenulls=True).over(w)).where("event_id % 2 = 1").select("event_id", "stated")


def colocation_interval(s, d):
    """Visits of others to a place within two hours, met hour by hour: three bins cover the interval."""
    v = event_visits(s, d).select("user_id", "event_id", "place", F.unix_seconds(F.col("ts").cast("timestamp")).alias("t"))
    left = v.withColumn("bin", F.explode(F.array(*(F.floor(F.col("t") / 7200) + k for k in (-1, 0, 1)))))
    right = v.select(F.col("user_id").alias("u2"), F.col("event_id").alias("e2"), "place", F.col("t").alias("t2"), F.floor(F.col("t") / 7200).alias("bin"))
    met = left.join(right, ["place", "bin"]).where("user_id <> u2 and abs(t - t2) <= 7200")
    return met.groupBy("user_id").agg(F.count("*").alias("met"))


def visit_gaps(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    t = F.unix_seconds(F.col("ts").cast("timestamp"))
    return event_visits(s, d).withColumn("gap", t - F.lag(t).over(w)).groupBy("user_id").agg(F.max("gap").alias("longest"), F.min("gap").alias("shortest"))


def rolling_24h(s, d):
    t = F.unix_seconds(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy(t).rangeBetween(-86400, 0)
    return event_visits(s, d).select("event_id", F.count("*").over(w).alias("n"))


def range_bracket(s, d):
    brackets = s.createDataFrame([("low", -1e9, 0.0, 10.0), ("mid", 0.0, 5000.0, 1.0), ("high", 5000.0, 1e9, 0.1)], "bracket string, lo double, hi double, eps double")
    c = table(s, d, "customer")
    return c.join(F.broadcast(brackets), F.expr("c_acctbal >= lo and c_acctbal < hi")).groupBy("bracket", "eps").agg(F.count("*").alias("users"))


def host_places(s, d):
    p = table(s, d, "pages").withColumn("host", F.regexp_extract("url", r"^https?://([^/]+)", 1))
    return p.groupBy("host").agg(F.count("*").alias("n"), F.countDistinct("page_id").alias("pages"))


def role_slot_matrix(s, d):
    return table(s, d, "conversations").groupBy("role", F.pmod("turn", F.lit(4)).cast("int").alias("slot")).agg(F.count("*").alias("n"), F.countDistinct("conv_id").alias("users"))


def sensitive_bit_estimate(s, d):
    """The rate of a rare bit by randomised response."""
    p = pv.flip_probability(2.0)
    noisy = table(s, d, "labels").withColumn("b", pv.randomize_bit(F.col("toxic"), p, uniform(SEED, "rr_a", F.col("doc_id")), uniform(SEED, "rr_b", F.col("doc_id"))))
    return noisy.agg(F.round(F.avg(pv.bit_weight(F.col("b"), p)), 6).alias("estimate"), F.round(F.avg("toxic"), 6).alias("truth"))


def embedding_topk(s, d):
    """For a stated query set, every 50th vector, the five others of the largest product: all queries against all rows."""
    v = table(s, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    q = v.where("vec_id % 50 = 0").select(F.col("vec_id").alias("query_id"), F.col("v").alias("q"))
    product = F.round(F.aggregate(F.zip_with("q", "v", lambda a, b: a * b), F.lit(0.0), lambda a, x: a + x), 6)
    both = q.join(v, F.expr("query_id <> vec_id")).withColumn("score", product)  # a stated query set against all rows
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return both.withColumn("rank", F.row_number().over(w)).where("rank <= 5").select("query_id", "rank", "vec_id", "score")


def embedding_class_means(s, d):
    v = table(s, d, "embeddings").select("label", F.posexplode("embedding").alias("k", "x"))
    return v.groupBy("label", "k").agg(F.round(F.avg(F.col("x").cast("double")), 6).alias("mean")).withColumn("k", F.col("k").cast("int"))


def neighbour_smoothing(s, d):
    """Shares of open visits by customer and nation, drawn to the other nations of the region."""
    v = order_visits(s, d)
    scores = v.groupBy("user_id", F.col("area").alias("loc")).agg(F.avg("label").alias("score"))
    n, r = table(s, d, "nation"), table(s, d, "nation").select(F.col("n_name").alias("near"), "n_regionkey")
    near = F.broadcast(n.join(r, "n_regionkey").where("n_name <> near").select(F.col("n_name").alias("loc"), "near"))  # 25 nations
    return extensions.neighbour_smooth(scores, near, 0.3).groupBy("loc").agg(F.round(F.avg("score"), 6).alias("score"), F.count("*").alias("n"))


def neighbour_measures(s, d):
    """What drawing a nation's score to its region does to the measures: known ratings, the user's mean elsewhere."""
    cells = experiment.event_cells(order_visits(s, d), 12, hourly=False, place="area", unit="months")
    marked = experiment.mask_unknown(cells, experiment.user_folds(cells).where("fold = 0"), 0.3)
    own = marked.where("held = 0").groupBy("user_id").agg(F.avg("rating").alias("mean"))
    score = F.when(F.col("held") == 0, F.col("rating")).otherwise(F.coalesce("mean", F.lit(0.5)))
    scored = marked.join(own, "user_id", "left").select("user_id", F.substring_index("item_id", "@", 1).alias("loc"), "truth", "held", score.alias("score"))
    scored = Rounds(s, "neighbours").keep(scored, "cells")
    n = table(s, d, "nation")
    near = F.broadcast(n.join(n.select(F.col("n_name").alias("near"), "n_regionkey"), "n_regionkey").where("n_name <> near").select(F.col("n_name").alias("loc"), "near"))  # 25 nations
    out = None
    for alpha in (0.0, 0.3, 0.6):
        shown = extensions.neighbour_smooth(scored, near, alpha).withColumn("decision", (F.round("score", 9) > 0.5).cast("int"))
        whole = metrics.rates(metrics.confusion(shown), "fpr", "recall").select("fpr", "recall")
        held = metrics.rates(metrics.confusion(shown.where("held = 1")), "reconstruction").select("reconstruction")
        row = whole.crossJoin(held).select(F.lit(alpha).alias("alpha"), "*").withColumns(r6("fpr", "recall", "reconstruction"))  # a row each
        out = row if out is None else out.unionByName(row)
    return out


def slot_transitions(s, d):
    return extensions.transitions(event_visits(s, d), WIDTH).withColumns(r6("p"))


def leakage(s, d):
    m = {(r.slot, r.next_slot): r.p for r in extensions.transitions(event_visits(s, d), WIDTH).collect()}  # 24 / WIDTH squared rows
    n = 24 // WIDTH
    rows = [[m.get((i, j), 0.0) for j in range(n)] for i in range(n)]
    bound, worst = extensions.temporal_leakage([0.5] * 6, rows), extensions.temporal_leakage([0.5] * 6)
    return s.createDataFrame([(k + 1, b, w) for k, (b, w) in enumerate(zip(bound, worst, strict=True))], "step int, leakage double, worst double").withColumns(r6("leakage", "worst"))


#: Sweeps: carrier, settings, and what differs from the rest; ``oracles`` reads the same table.
SWEEPS: dict[str, tuple[Callable, list[dict], dict]] = {
    "sweep_width": (event_visits, [BASE | {"width": w} for w in (2, 3, 4, 6, 8, 12)], {"hourly": True}),
    "sweep_width_months": (order_visits, [BASE | {"width": w, "place": "area"} for w in (1, 2, 3, 4, 6, 12)], {"unit": "months"}),
    "sweep_eps": (event_visits, [BASE | {"eps": e} for e in (0.0001, 0.0003, 0.001, 0.003, 0.005, 0.01, 1.0, 10.0, 100.0)], {}),
    "sweep_unknown": (event_visits, [BASE | {"unknown": h / 10} for h in range(1, 10)], {}),
    "sweep_unknown_lineitem": (order_visits, [BASE | {"unknown": h / 10, "place": "area"} for h in range(1, 10)], {"unit": "months"}),
    "sweep_location": (order_visits, [BASE | {"place": k} for k in ("category", "area", "category_area", "place")], {"unit": "months"}),
    "compare_methods": (event_visits, [BASE | {"eps": 10.0}], {"methods": ("plain", "private", "central", "cf_user", "cf_item", "majority")}),
    "ablation": (event_visits, [BASE | {"eps": PRIVATE.eps}], {"methods": ("bits", "grads", "both", "none", "central")}),
}
SWEEP_ROUNDS, TOLERANCE, TARGET = 6, 0.03, 0.55


#: Averages of sweeps that this application has made: table by query and input files.
_AVERAGES: dict[tuple, str] = {}


def swept(name: str) -> Query:
    """A setting's measures, averaged over all repetitions of all folds. Made once for each input in an application."""

    def run(s, d):
        carrier, grid, how = SWEEPS[name]
        visits = carrier(s, d)
        key = (s.sparkContext.applicationId, name, REPEATS, REPEATS_LARGE, tuple(sorted(visits.inputFiles())), visits.count())
        if key not in _AVERAGES:
            runs = FOLDS * (REPEATS if carrier is event_visits else REPEATS_LARGE)
            out = experiment.averaged(experiment.sweep(visits, grid, folds=FOLDS, runs=runs, rounds=SWEEP_ROUNDS, **how))
            out = out.withColumns(r6(*(c for c in out.columns if c.rpartition("_")[2] in ("mean", "sd", "half"))))
            path = f"{shared_root(s)}/averages-{name}-{uuid.uuid4().hex}"
            out.write.parquet(path)
            _AVERAGES[key] = path
        return s.read.parquet(_AVERAGES[key])

    return run


def choose_parameters(s, d):
    """The choice of parameters, made on the sweeps themselves."""
    return experiment.choice(*(swept(f"sweep_{k}")(s, d) for k in ("width", "eps", "unknown")), TOLERANCE, TARGET)


def gap_pivot(s, d):
    """Utility of the private method minus that of the plain one, by setting."""
    return metrics.gap(swept("sweep_unknown")(s, d), ("unknown",), "reconstruction_mean").withColumns(r6("private", "plain", "gap"))


def utility_slope(s, d):
    return experiment.utility_slope(swept("sweep_eps")(s, d), "reconstruction_mean").select("method", "eps", F.round("u", 6).alias("u"), F.round("slope", 6).alias("slope"))


def _streamed(s, d, name: str, make, mode: str = "append") -> DataFrame:
    """A stream over a folder that holds the events, run to its end and read back."""
    root = f"{shared_root(s)}/{name}-{uuid.uuid4().hex}"
    table(s, d, "events").write.mode("overwrite").parquet(f"{root}/in")
    q = make(checkins.read_events(s, f"{root}/in")).writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/state").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return s.read.parquet(f"{root}/out")


def stream_slot_counts(s, d):
    out = _streamed(s, d, "slots", lambda e: checkins.slot_counts(e, WIDTH))
    return out.select(F.date_format("slot_start", "yyyy-MM-dd HH:mm").alias("slot_start"), "event_type", "n")


def gate_cells(s, d):
    """``user_id, item, decision`` of every cell: the rating where there is one, else the recommendation."""
    t, X, Z = fitted_model(s, d)
    asked = preferences.unknown_cells(t.select("user_id"), t, t, "item_id")
    made = t.select("user_id", "item_id", F.col("rating").cast("int").alias("decision")).unionByName(predict.recommend(asked, X, Z, D).select("user_id", "item_id", "decision"))
    return made.withColumnRenamed("item_id", "item")


def stream_gate(s, d):
    cells = gate_cells(s, d)
    keyed = lambda e: checkins.gate(e.withColumn("item", preferences.item_key(F.col("event_type"), g.time_slot(F.col("ts"), WIDTH))), cells)
    return _streamed(s, d, "gate", keyed).groupBy("event_type").agg(F.count_if("released").alias("released"), F.count_if(~F.col("released")).alias("hidden"))


def stream_sessions(s, d):
    out = _streamed(s, d, "sessions", lambda e: checkins.sessions(e, "24 hours"))
    return out.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))


def stream_sliding(s, d):
    """Visits by windows of six hours that start every three."""
    out = _streamed(s, d, "sliding", lambda e: checkins.sliding(e, 6, 3))
    return out.select(F.date_format("start", "yyyy-MM-dd HH:mm").alias("start"), "n")


def stream_dedup(s, d):
    """Reports that were sent twice count once."""
    return _streamed(s, d, "dedup", lambda e: checkins.dedup(e.unionByName(e))).groupBy("event_type").agg(F.count("*").alias("n"))


def stream_matched(s, d):
    """Stated answers, the even events, with the same user's check-ins of the six hours before."""
    out = _streamed(s, d, "match", lambda e: checkins.match(e.where("event_id % 2 = 0"), e.where("event_id % 2 = 1"), "6 hours"))
    return out.groupBy("user_id").agg(F.count("*").alias("pairs"))


def stream_refit(s, d):
    """The last label of every user and category, kept up by batches."""
    root = f"{shared_root(s)}/refit-{uuid.uuid4().hex}"
    table(s, d, "events").write.parquet(f"{root}/in")
    seen = []
    checkins.refit(checkins.read_events(s, f"{root}/in"), f"{root}/out", f"{root}/state", lambda df, n: seen.append(n)).awaitTermination()
    return s.read.parquet(f"{root}/out/{seen[-1]}").groupBy("event_type").agg(F.count("*").alias("users"), F.sum("label").alias("open"))


def stream_totals(s, d):
    """Running totals by category, the whole table of them after every batch (complete mode)."""
    root = f"{shared_root(s)}/totals-{uuid.uuid4().hex}"
    table(s, d, "events").write.parquet(f"{root}/in")
    name = f"totals_{uuid.uuid4().hex}"
    checkins.run_to_table(checkins.read_events(s, f"{root}/in").groupBy("event_type").agg(F.count("*").alias("n")), name, f"{root}/state", "complete")
    return s.table(name)


def masked_exact(s, d):
    t = triples(s, d)
    return experiment.mask_unknown(t, experiment.user_folds(t).where("fold = 0"), 0.3, exact=True)


def estimator_errors(s, d):
    """Bias and variance of the visit estimate over twenty rounds of fresh bits."""
    p = pv.flip_probability(1.0)
    cells = bit_cells(s, d).crossJoin(F.broadcast(s.range(1, 21).select(F.col("id").cast("int").alias("round"))))
    key = [F.col("user_id"), F.col("item_id"), F.col("round")]
    bits = cells.withColumn("ybit", pv.randomize_bit(F.col("y"), p, uniform(SEED, "bit_flip", *key), uniform(SEED, "bit_coin", *key)))
    by_round = bits.groupBy("item_id", "round").agg(F.avg(pv.bit_weight(F.col("ybit"), p)).alias("estimate"), F.avg("y").alias("truth"))
    return metrics.estimator_error(by_round, "truth", ("item_id",)).withColumns(r6("bias", "variance"))


def survey_of_users(s, d):
    """Survey and trajectories from one carrier: a share of users answers, the rest is only seen."""
    v = event_visits(s, d).withColumn("kind", F.when(uniform(SEED, "survey", F.col("user_id")) < 0.13, "survey").otherwise("trajectory"))
    return v.groupBy("kind").agg(F.countDistinct("user_id").alias("users"), F.count("*").alias("records"), F.countDistinct("place").alias("places"))


def side_by_side(first: DataFrame, second: DataFrame) -> DataFrame:
    """Item factors of two models; a full join keeps items of either."""
    return first.withColumnsRenamed({"z0": "a0", "z1": "a1"}).join(second, "item_id", "full")


def compare_models(s, d):
    """Item factors after one and three rounds side by side."""
    return side_by_side(fitted(rounds=1)(s, d), fitted()(s, d))


def silent_customers(s, d):
    """Customers without an urgent order, by segment."""
    urgent = table(s, d, "orders").where("o_orderpriority = '1-URGENT'")
    return table(s, d, "customer").join(urgent, F.expr("c_custkey = o_custkey"), "left_anti").groupBy("c_mktsegment").agg(F.count("*").alias("n"))


def folds_and_rest(s, d):
    """Cells of one fold and of the others: together everything, in common nothing."""
    t = triples(s, d).join(experiment.user_folds(triples(s, d)), "user_id")
    a, b, cells = t.where("fold = 0").drop("fold"), t.where("fold <> 0").drop("fold"), triples(s, d)
    rows = [a.intersectAll(b).agg(F.lit("common").alias("part"), F.count("*").alias("n")), cells.exceptAll(a.unionByName(b)).agg(F.lit("missing").alias("part"), F.count("*").alias("n")), a.unionByName(b).agg(F.lit("all").alias("part"), F.count("*").alias("n"))]
    return rows[0].unionByName(rows[1]).unionByName(rows[2])


def measures_long(s, d):
    """Measures as rows instead of columns."""
    wide = metrics.rates(metrics.confusion(scored_planted(s, d)), "fpr", "recall", "reconstruction")
    return wide.unpivot([], ["fpr", "recall", "reconstruction"], "measure", "value").withColumns(r6("value"))


def grouped_sets(s, d):
    cells = scored_planted(s, d).withColumn("slot", F.substring_index("item_id", "@", -1))
    return cells.groupingSets([["slot"], ["held"], []], "slot", "held").agg(F.count("*").alias("n"), F.round(F.avg("decision"), 6).alias("share"))


def lateral_top(s, d):
    """The two most visited places of every user, by a lateral join."""
    v = event_visits(s, d).groupBy("user_id", "place").agg(F.count("*").alias("n"))
    users = v.select(F.col("user_id").alias("u")).distinct()
    best = v.where(F.col("user_id") == F.col("u").outer()).orderBy(F.desc("n"), "place").limit(2)
    return users.lateralJoin(best.select("place", "n")).select(F.col("u").alias("user_id"), "place", "n")


def mean_vector_udaf(s, d):
    from ..functions.sqlface import mean_vector

    means = table(s, d, "embeddings").groupBy("label").agg(mean_vector()("embedding").alias("m"))
    return means.select("label", F.posexplode("m").alias("k", "x")).select("label", F.col("k").cast("int").alias("k"), F.round("x", 6).alias("mean"))


def time_ladder(s, d):
    from ..functions.sqlface import register

    register(s)
    hours = event_visits(s, d).groupBy(F.hour("ts").alias("hour")).agg(F.count("*").alias("n"))
    hours.createOrReplaceTempView("_hours")
    return s.sql("SELECT width, slot, sum(n) AS n FROM _hours, LATERAL time_ladder(hour) GROUP BY width, slot")


def observed_loss(s, d):
    """Loss and rows of a pass, observed while the pass does something else."""
    from pyspark.sql import Observation

    t, X, Z = start(s, d)
    seen = Observation("loss")
    res = factorization.residuals(t, X, Z, D).observe(seen, F.avg(F.col("e") * F.col("e")).alias("data"), F.count(F.lit(1)).alias("rows"))
    factorization.item_gradient(res, D).write.format("noop").mode("overwrite").save()
    got = seen.get
    return s.createDataFrame([(round(got["data"], 6), got["rows"])], "data double, rows long")


def fold_in_shares(s, d):
    """New users who give a share of their ratings: how much of the rest comes out right."""
    cells = planted_cells(s, d)
    new = experiment.user_folds(cells).where("fold = 0")
    m = factorization.fit_plain(cells.join(new, "user_id", "left_anti"), factorization.FitConfig(d=3, rounds=12))
    out = None
    for share in (0.1, 0.3, 0.5, 0.7, 0.9):
        own = experiment.mask_unknown(cells.join(new, "user_id", "left_semi"), new, 1 - share)
        x = factorization.fold_in(own.where("held = 0"), m.Z, 3, 0.1)
        asked = own.where("held = 1").select("user_id", "item_id", "truth")
        scored = predict.score(asked, x, m.Z, 3).withColumn("decision", (F.col("score") > 0.5).cast("int"))
        row = metrics.rates(metrics.confusion(asked.join(scored.select("user_id", "item_id", "decision"), ["user_id", "item_id"], "left").withColumn("decision", F.coalesce("decision", F.lit(0)))), "reconstruction").select(F.lit(share).alias("known_share"), F.round("reconstruction", 6).alias("reconstruction"))
        out = row if out is None else out.unionByName(row)
    return out


def budgeted_stream(s, d):
    """Reports accepted and refused under a budget for ten."""
    out = _streamed(s, d, "budget", lambda e: checkins.budgeted_reports(e, 0.1, 1.0))
    return out.groupBy("user_id").agg(F.count_if("accepted").alias("accepted"), F.count_if(~F.col("accepted")).alias("refused"))


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {f"slots_w{w}": slots(w) for w in (2, 3, 4, 6, 8, 12)}
    out |= {"day_part_counts": counted(part=g.day_part), "day_kind_counts": counted(kind=g.day_kind, name=g.day_name), "composite_time_keys": counted(key=lambda ts: g.time_key(ts, ("month", "kind", "part")))}
    out |= {f"location_keys_{k}": location_keys(k) for k in ("category", "area", "category_area", "category_place", "place")}
    out |= {f"prefs_{r}": prefs(r) for r in preferences.RULES}
    out |= {"dense_ids_rank": dense_ids("rank"), "dense_ids_range": dense_ids("range")}
    out |= {f"transfer_{m}": transferred(m) for m in ("rate", "archetype", "hybrid")}
    out |= {"described_events": described(event_visits), "described_orders": described(order_visits)}
    out |= {f"masked_cells_h{h}": masked_cells(h) for h in range(1, 10)}
    out |= {"fit_plain_k1": fitted(rounds=1), "fit_plain_k3": fitted(), "fit_plain_alternate": fitted(order="alternate"), "fit_plain_by_users": fitted(norm="users"), "fit_plain_inverse_step": fitted(step=factorization.StepSize("inverse", 0.5)), "fit_plain_projected": fitted(max_norm=0.5), "fit_plain_blocks": fitted(blocks=2, norm="users")}
    out |= {"mean_threshold": mean_threshold("all_cells"), "mean_threshold_observed": mean_threshold("observed"), "mean_threshold_per_user": mean_threshold("per_user")}
    out |= {"noisy_bits_fresh": noisy_bits("fresh"), "noisy_bits_permanent": noisy_bits("permanent")}
    out |= {f"clipped_gradients_{k}": clipped_gradients(k) for k in ("l1", "l2", "coordinate")}
    out |= {"aggregated_gradient_affine": aggregated("pair"), "aggregated_gradient_product": aggregated("product")}
    out |= {"fit_private_k1": fit_private(rounds=1), "fit_private_k2": fit_private(), "fit_private_product": fit_private(report="product"), "fit_private_server_side": fit_private(user_side="server", rounds=1), "fit_private_sampled": fit_private(report_sample=5, rounds=1), "fit_private_fast": fit_private("fast"), "fit_central": fit_private("central")}
    out |= {"cf_user": cf("user"), "cf_item": cf("item"), "cf_user_pearson": cf("user", "pearson"), "cf_item_jaccard": cf("item", "jaccard")}
    out |= {f"majority_{b}": majority(b) for b in ("global", "item", "user", "bias")}
    out |= {"constant_hide": constant(0), "constant_publish": constant(1)}
    out |= {name: swept(name) for name in SWEEPS}
    named = (calendar_slots, month_slots, location_ladder, prefs_supported, matrix_stats_events, matrix_stats_lineitem, degree_quantiles, survey_rates, archetypes_cosine, user_folds, user_folds_exact, init_factors, score_cells, loss_initial, loss_dense, user_gradient, item_gradient, fit_trace, mean_threshold_grid, unknown_cells, recommend, top_k, flip_probability_grid, visit_estimates, bits_by_user, laplace_noise, client_reports, synthesized_noise, protocol_round, budget_ledger, budget_ledger_server, ledger_totals, private_round, sampled_reports, aggregated_by_levels, observed_traffic, factor_norms, privacy_audit, fold_in, fold_in_descent, stream_sliding, stream_dedup, stream_matched, stream_refit, stream_totals, als_baseline, coin, k_anonymous, coarsened, confusion, fpr_recall, reconstruction, rmse, metrics_cube, traffic, planted_triples, asof_preference, colocation_interval, visit_gaps, rolling_24h, range_bracket, host_places, role_slot_matrix, sensitive_bit_estimate, embedding_topk, embedding_class_means, neighbour_smoothing, neighbour_measures, slot_transitions, leakage, choose_parameters, gap_pivot, utility_slope, stream_slot_counts, stream_gate, stream_sessions, masked_exact, estimator_errors, survey_of_users, compare_models, silent_customers, folds_and_rest, measures_long, grouped_sets, lateral_top, mean_vector_udaf, time_ladder, observed_loss, fold_in_shares, budgeted_stream)
    return out | {f.__name__: f for f in named}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recommendations for every cell without a rating: (user_id, item, score, decision)."""
    visits = event_visits(spark, sf_dir)
    t = preferences.build(visits, g.location_key("category_place"), slot()).select("user_id", F.col("item").alias("item_id"), "rating")
    m = factorization.fit_plain(t, factorization.FitConfig(d=D, rounds=3, norm="ratings"))
    cells = preferences.unknown_cells(t.select("user_id"), t, t, "item_id")
    return predict.recommend(cells, m.X, m.Z, D).withColumnRenamed("item_id", "item")
