"""Factorisation under local differential privacy.

Client stage, by user: for every item a noisy visit bit and a noisy clipped gradient.
Server stage: sums by item over reports alone, debiased. The dense report of every
item is the method as described and grows with users times items; a deployment sends
a data-independent sample of items, and a simulation draws the noise of all unvisited
cells by item at once, which has the same distribution.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import gaussian, hash_bits, uniform
from ..functions.privacy import Budget, bit_weight, clip, flip_probability, flip_probability_column, laplace, randomize_bit, secure_uniform
from ..sources.rounds import Rounds
from .factorization import FactorModel, FitConfig, StepSize, cols, init_factors, residuals, step, user_gradient
from .preferences import index


@dataclass(frozen=True)
class PrivateConfig(FitConfig):
    eps: float = 1.0
    policy: str = "per_report"
    bit_share: float = 0.5
    clip: float = 1.0
    clip_norm: str = "l1"
    bit_mode: str = "fresh"
    report: str = "pair"
    user_side: str = "client"
    user_share: float = 0.25
    report_sample: int | None = None
    protect: tuple[str, ...] = ("bits", "grads")
    noise: str = "seeded"
    max_norm: float | None = 2.0
    step: StepSize = StepSize()

    def __post_init__(self) -> None:
        super().__post_init__()
        if self.report not in ("pair", "product") or self.bit_mode not in ("fresh", "permanent") or self.user_side not in ("client", "server") or self.noise not in ("seeded", "secure"):
            raise ValueError("unknown report, bit_mode, user_side or noise")

    def budget(self, n_items: int) -> Budget:
        """A sampled report has ``report_sample`` items in a round, and the same ones in all rounds if bits are permanent."""
        share = self.user_share if self.user_side == "server" else 0.0
        return Budget(self.policy, self.eps, self.bit_share, self.rounds, min(self.report_sample or n_items, n_items), self.bit_mode == "permanent", share)

    def mechanism(self, n_items: int) -> tuple[float, float]:
        """Flip probability and Laplace scale of one round."""
        bit, grad = self.budget(n_items).per_round()
        p = flip_probability(bit) if "bits" in self.protect else 0.0
        return p, (2 * self.clip / grad if "grads" in self.protect else 0.0)

    def user_scale(self, n_items: int) -> float:
        """Laplace scale of a user gradient, the third release of a round."""
        return 2 * self.clip / self.budget(n_items).user_gradient() if "grads" in self.protect else 0.0

    def draw(self, purpose: str, *parts: Column) -> Column:
        return secure_uniform(purpose, *parts) if self.noise == "secure" else uniform(self.seed, purpose, *parts)


def noisy_bits(cells: DataFrame, p: float | Column, seed: int, round_: int = 0, mode: str = "fresh", noise: str = "seeded") -> DataFrame:
    """``ybit`` for cells (user_id, item_id, y).

    Permanent bits are the same in every round: seeded by the cell alone, or, if
    ``noise`` is secure, drawn once by whoever keeps the result.
    """
    part = [F.col("user_id"), F.col("item_id")] + ([F.lit(round_)] if mode == "fresh" else [])
    draw = (lambda purpose: secure_uniform(purpose, *part)) if noise == "secure" else (lambda purpose: uniform(seed, purpose, *part))
    return cells.withColumn("ybit", randomize_bit(F.col("y"), p, draw("bit_flip"), draw("bit_coin")))


def estimate_visits(bits: DataFrame, p: float) -> DataFrame:
    """Unbiased share of users who visited each item, from noisy bits alone."""
    return bits.groupBy("item_id").agg(F.avg(bit_weight(F.col("ybit"), p)).alias("estimate"))


def clipped_gradients(rated: DataFrame, cfg: PrivateConfig) -> DataFrame:
    """``g0..`` of rated cells: -2 e x inside the ball."""
    raw = [-2.0 * F.col("e") * F.col(c) for c in cols("x", cfg.d)]
    return rated.select("user_id", "item_id", *(g.alias(f"g{k}") for k, g in enumerate(clip(raw, cfg.clip, cfg.clip_norm))))


def sampled_cells(users: DataFrame, items: DataFrame, cfg: PrivateConfig, round_: int) -> DataFrame:
    """``user_id, item_id``: exactly ``report_sample`` items of each user (or all there are), whatever the data.

    The items stand on a ring in order of their hashes; a user takes those that follow
    a place drawn for the user. Every item has the same chance, and no grid is built.
    """
    key = [F.lit(round_)] if cfg.bit_mode == "fresh" else []
    m = items.count()
    s = min(cfg.report_sample or m, m)
    ring = items.select("item_id", F.struct(hash_bits(cfg.seed, "ring", F.col("item_id"), *key).alias("h"), F.col("item_id").alias("i")).alias("ring"))
    ring = ring.join(index(ring, "ring", "range"), "ring").select("item_id", F.col("id").alias("place"))
    first = F.floor(cfg.draw("sample", F.col("user_id"), *key) * m).cast("long")
    asked = users.select("user_id", first.alias("first"), F.explode(F.sequence(F.lit(0), F.lit(s - 1))).alias("step")).select("user_id", F.pmod(F.col("first") + F.col("step"), F.lit(m)).alias("place"))
    return asked.join(ring, "place").select("user_id", "item_id")


def reported_cells(X: DataFrame, Z: DataFrame, cfg: PrivateConfig, round_: int) -> DataFrame:
    """``user_id, item_id`` of a round's reports: the sampled ones, or all, which is the dense report of the method."""
    if cfg.report_sample is not None:
        return sampled_cells(X, Z.select("item_id"), cfg, round_)
    return X.select("user_id").crossJoin(Z.select("item_id"))


def client_reports(X: DataFrame, ratings: DataFrame, Z: DataFrame, cfg: PrivateConfig, round_: int, p: float, scale: float, kept_bits: DataFrame | None = None, levels: DataFrame | None = None) -> DataFrame:
    """``item_id, ybit, g0.. `` for every user and item (or the sampled ones); no clear value leaves.

    An unvisited cell has the zero gradient before noise. ``kept_bits`` (user_id,
    item_id, ybit) are permanent bits drawn before. ``levels`` (user_id, eps) gives each
    user a level of their own: p and the scale follow it, and the report carries the
    weight of its bit, which the client works out from its own p.
    """
    grads = clipped_gradients(residuals(ratings, X, Z, cfg.d), cfg)
    cells = kept_bits.select("user_id", "item_id") if kept_bits is not None else reported_cells(X, Z, cfg, round_)
    joined = cells.join(grads, ["user_id", "item_id"], "left").withColumn("y", F.col("g0").isNotNull().cast("int"))
    own_p, own_scale = F.lit(float(p)), F.lit(float(scale))
    if levels is not None:
        bit, grad = replace(cfg, eps=1.0).budget(Z.count()).per_round()  # what a level of 1 spends; spending is linear in eps
        own_p, own_scale = flip_probability_column(F.col("eps") * bit), 2 * cfg.clip / (F.col("eps") * grad)
        joined = joined.join(levels.select("user_id", "eps"), "user_id")
    if kept_bits is not None:
        bits = joined.join(kept_bits.select("user_id", "item_id", "ybit"), ["user_id", "item_id"])
    else:
        bits = noisy_bits(joined, own_p, cfg.seed, round_, cfg.bit_mode, cfg.noise)
    key = [F.col("user_id"), F.col("item_id"), F.lit(round_)]
    noisy = [(F.coalesce(F.col(f"g{k}"), F.lit(0.0)) + laplace(cfg.draw("lap", *key, F.lit(k)), own_scale)).alias(f"g{k}") for k in range(cfg.d)]
    weight = [] if levels is None else [bit_weight(F.col("ybit"), own_p).alias("w")]
    out = bits.select("user_id", "item_id", "ybit", *noisy, *weight)
    if cfg.report == "product":
        out = out.select("user_id", "item_id", *((F.col("ybit") * F.col(f"g{k}")).alias(f"g{k}") for k in range(cfg.d)))
    return out


def aggregate_reports(reports: DataFrame, cfg: PrivateConfig, p: float, weight: Column | None = None) -> DataFrame:
    """Mean gradient by item from reports alone.

    Pairs are debiased by the bit's weight (``weight`` for one by user). Products have
    the mean (1 - p/2) times the truth, as unvisited cells are zero.
    """
    if cfg.report == "product":
        parts = [F.avg(F.col(f"g{k}")) / (1 - p / 2) for k in range(cfg.d)]
    else:
        w = bit_weight(F.col("ybit"), p) if weight is None else weight
        parts = [F.avg(w * F.col(f"g{k}")) for k in range(cfg.d)]
    return reports.groupBy("item_id").agg(*(x.alias(f"g{k}") for k, x in enumerate(parts)))


def synthesize_noise(items: DataFrame, d: int, seed: int, round_: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """``keys, item_id, s0..``: summed noise of the users without a rating for an item, as one normal draw.

    ``items`` has ``rated``, ``n`` (users), ``p`` and ``scale``. The noise of one
    unvisited cell, the weight of a zero bit times a Laplace draw, has mean zero and
    variance (p/2)(1 - p/2) / (1 - p)^2 times twice the squared scale; coordinates share
    the bit but are uncorrelated. The sum over n - rated cells is drawn as a normal with
    that variance: exact in mean and variance, and near the sum's law from some dozens
    of cells on. A simulator's step, never a protocol.
    """
    q, n = F.col("p") / 2, F.col("n") - F.col("rated")
    spread = F.sqrt(n * q * (1 - q) * 2.0) / (1 - F.col("p")) * F.col("scale")
    part = [*(F.col(k) for k in keys), F.col("item_id"), F.lit(round_)]
    return items.select(*keys, "item_id", *((gaussian(seed, "synth", *part, F.lit(k)) * spread).alias(f"s{k}") for k in range(d)))


def fit_runs(triples: DataFrame, eps_of: list[tuple[int, float]], cfg: PrivateConfig, central: bool = False) -> FactorModel:
    """Many private fits in one plan: (run, user_id, item_id, rating) with an eps for each run.

    The noise of unvisited cells is synthesised; ``central`` adds Laplace noise to exact
    sums instead. A round is the same few jobs for any number of runs. A simulation: its
    draws are seeded, whatever ``cfg.noise`` says.
    """
    spark, keys, d = triples.sparkSession, ["run"], cfg.d
    scratch = Rounds(spark, "private-runs")
    by_user = ["run", "user_id"]
    data = scratch.keep(triples.select("run", "user_id", "item_id", "rating"), "triples", by_user)
    size = data.groupBy("run").agg(F.countDistinct("user_id").alias("n"), F.countDistinct("item_id").alias("m")).collect()  # a row for each run
    eps = dict(eps_of)
    rows = [(r.run, r.n, r.m, *replace(cfg, eps=eps[r.run]).mechanism(r.m)) for r in size]
    params = spark.createDataFrame([(r, n, m, 0.0 if central else p, s) for r, n, m, p, s in rows], "run int, n long, m long, p double, scale double")
    X = scratch.keep(init_factors(data.select("run", "user_id").distinct(), "user_id", "x", d, cfg.seed), "x-0", by_user)
    items = scratch.keep(data.groupBy("run", "item_id").agg(F.count("*").alias("rated")).join(F.broadcast(params), "run"), "items")
    Z = scratch.keep(init_factors(items.select("run", "item_id"), "item_id", "z", d, cfg.seed), "z-0")
    for t in range(1, cfg.rounds + 1):
        gamma = cfg.step.at(t)
        res = residuals(data, X, Z, d, ("run",)).join(F.broadcast(params), "run")
        raw = clip([-2.0 * F.col("e") * F.col(c) for c in cols("x", d)], cfg.clip, cfg.clip_norm)
        key = [F.col("run"), F.col("user_id"), F.col("item_id"), F.lit(t)]
        if central:
            sums = res.select("run", "item_id", *(g.alias(f"g{k}") for k, g in enumerate(raw))).groupBy("run", "item_id").agg(*(F.sum(f"g{k}").alias(f"g{k}") for k in range(d))).join(F.broadcast(params), "run")
            grad = sums.select("run", "item_id", *(((F.col(f"g{k}") + laplace(uniform(cfg.seed, "central", F.col("run"), F.col("item_id"), F.lit(t), F.lit(k)), F.col("scale"))) / F.col("n")).alias(f"g{k}") for k in range(d)))
        else:
            bit = randomize_bit(F.lit(1), F.col("p"), uniform(cfg.seed, "bit_flip", *key), uniform(cfg.seed, "bit_coin", *key))
            noisy = res.select("run", "item_id", bit_weight(bit, F.col("p")).alias("w"), *((g + laplace(uniform(cfg.seed, "lap", *key, F.lit(k)), F.col("scale"))).alias(f"g{k}") for k, g in enumerate(raw)))
            rated = noisy.groupBy("run", "item_id").agg(*(F.sum(F.col("w") * F.col(f"g{k}")).alias(f"g{k}") for k in range(d)))
            noise = synthesize_noise(items, d, cfg.seed, t, ("run",)).join(F.broadcast(params), "run")
            grad = noise.join(rated, ["run", "item_id"], "left").select("run", "item_id", *(((F.coalesce(f"g{k}", F.lit(0.0)) + F.col(f"s{k}")) / F.col("n")).alias(f"g{k}") for k in range(d)))
        gx = user_gradient(res, d, ("run",), weight=1.0 / F.col("m"))
        newZ = scratch.keep(step(Z, grad, "item_id", "z", gamma, cfg.lam_z, cfg, ("run",)), f"z-{t}")
        X, Z = scratch.keep(step(X, gx, "user_id", "x", gamma, cfg.lam_x, cfg, ("run",)), f"x-{t}", by_user), newZ
        scratch.only("triples", "items", f"x-{t}", f"z-{t}")
    scratch.drop("triples", "items")
    return FactorModel(X, Z, [], cfg)


def fit_private(triples: DataFrame, cfg: PrivateConfig, mode: str = "reports") -> FactorModel:
    """``cfg.rounds`` rounds; ``reports`` sends every report, ``fast`` synthesises the unvisited ones, ``central`` trusts the server.

    Rounds are fixed: stopping by the data would spend budget of its own. With
    ``user_side='server'`` user gradients are clipped and noised too.
    """
    if mode != "reports":
        if mode not in ("fast", "central"):
            raise ValueError(f"unknown mode {mode}")
        model = fit_runs(triples.withColumn("run", F.lit(0)), [(0, cfg.eps)], cfg, mode == "central")
        return FactorModel(model.X.drop("run"), model.Z.drop("run"), [], cfg)
    scratch = Rounds(triples.sparkSession, "private")
    data = scratch.keep(triples.select("user_id", "item_id", "rating"), "triples", ["user_id"])
    X = scratch.keep(init_factors(data.select("user_id").distinct(), "user_id", "x", cfg.d, cfg.seed), "x-0", ["user_id"])
    Z = scratch.keep(init_factors(data.select("item_id").distinct(), "item_id", "z", cfg.d, cfg.seed), "z-0")
    m = Z.count()
    p, scale = cfg.mechanism(m)
    kept = None
    if cfg.bit_mode == "permanent" and cfg.noise == "secure":
        cells = reported_cells(X, Z, cfg, 0).join(data.select("user_id", "item_id", F.lit(1).alias("y")), ["user_id", "item_id"], "left").withColumn("y", F.coalesce("y", F.lit(0)))
        kept = scratch.keep(noisy_bits(cells, p, cfg.seed, 0, "permanent", "secure").select("user_id", "item_id", "ybit"), "bits")
    for t in range(1, cfg.rounds + 1):
        gamma = cfg.step.at(t)
        sent = client_reports(X, data, Z, cfg, t, p, scale, kept)
        if cfg.noise == "secure":
            sent = scratch.keep(sent, f"reports-{t}")  # a draw is made once
        grad = aggregate_reports(sent, cfg, p)
        gx = user_gradient(residuals(data, X, Z, cfg.d), cfg.d, weight=F.lit(1.0 / m))
        if cfg.user_side == "server":
            held = clip([F.col(f"g{k}") for k in range(cfg.d)], cfg.clip, cfg.clip_norm)
            gx = gx.select("user_id", *((g + laplace(cfg.draw("lap_user", F.col("user_id"), F.lit(t), F.lit(k)), cfg.user_scale(m))).alias(f"g{k}") for k, g in enumerate(held)))
        newZ = scratch.keep(step(Z, grad, "item_id", "z", gamma, cfg.lam_z, cfg), f"z-{t}")
        X, Z = scratch.keep(step(X, gx, "user_id", "x", gamma, cfg.lam_x, cfg), f"x-{t}", ["user_id"]), newZ
        scratch.only("triples", "bits", f"x-{t}", f"z-{t}")
    scratch.only(f"x-{cfg.rounds}", f"z-{cfg.rounds}")
    return FactorModel(X, Z, [], cfg)
