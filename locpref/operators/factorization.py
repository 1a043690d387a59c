"""Regularised matrix factorisation by gradient descent on long-form triples.

Factors are tables with one column per coordinate, so residuals, gradients and steps
are plain expressions and sums that run in generated code. Triples and user factors are
bucketed by user, so the user side of a round meets without a shuffle; the item side's
sums are combined before theirs. Several independent
fits (folds, repetitions, settings) run as one: ``run`` is part of every key, and a
round is the same few jobs however many fits there are.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import hash_bits, uniform
from ..sources.rounds import Rounds


@dataclass(frozen=True)
class StepSize:
    """``constant``, ``inverse`` (g/t), ``root`` (g/sqrt t) or ``bold`` (up 5 % after a better round, halved after a worse one)."""

    kind: str = "constant"
    first: float = 0.5

    def at(self, t: int, last: float | None = None, loss: tuple[float, float] | None = None) -> float:
        if self.kind == "constant":
            return self.first
        if self.kind == "inverse":
            return self.first / t
        if self.kind == "root":
            return self.first / math.sqrt(t)
        if self.kind != "bold":
            raise ValueError(f"unknown schedule {self.kind}")
        if last is None or loss is None:
            return self.first
        return last * (1.05 if loss[1] <= loss[0] else 0.5)


@dataclass(frozen=True)
class FitConfig:
    d: int = 4
    rounds: int = 60
    step: StepSize = field(default_factory=StepSize)
    lam_x: float = 1e-4
    lam_z: float = 1e-4
    norm: str = "users"
    order: str = "joint"
    tol: float | None = None
    max_norm: float | None = None
    blocks: int | None = None
    trace: bool = False
    seed: int = 42

    def __post_init__(self) -> None:
        if self.norm not in ("ratings", "users") or self.order not in ("joint", "alternate") or self.d < 1:
            raise ValueError("norm is ratings or users, order joint or alternate, d positive")


@dataclass
class FactorModel:
    """X (run, user_id, x0..), Z (run, item_id, z0..) and the trace of rounds."""

    X: DataFrame
    Z: DataFrame
    trace: list[dict]
    config: FitConfig


def cols(p: str, d: int) -> list[str]:
    return [f"{p}{k}" for k in range(d)]


def dot(d: int, a: str = "x", b: str = "z") -> Column:
    parts = [F.col(f"{a}{k}") * F.col(f"{b}{k}") for k in range(d)]
    return sum(parts[1:], parts[0])


def init_factors(ids: DataFrame, key: str, prefix: str, d: int, seed: int = 42, scale: float = 0.75) -> DataFrame:
    """Around scale/sqrt(d), apart by a seeded draw, so that coordinates can part."""
    draw = lambda k: F.lit(scale / math.sqrt(d)) * (F.lit(0.5) + uniform(seed, f"init_{prefix}", F.col(key), F.lit(k)))
    return ids.select("*", *(draw(k).alias(f"{prefix}{k}") for k in range(d)))


def residuals(triples: DataFrame, X: DataFrame, Z: DataFrame, d: int, keys: tuple[str, ...] = ()) -> DataFrame:
    return triples.join(X, [*keys, "user_id"]).join(Z, [*keys, "item_id"]).withColumn("e", F.col("rating") - dot(d))


def loss(triples: DataFrame, X: DataFrame, Z: DataFrame, cfg: FitConfig, keys: tuple[str, ...] = ()) -> DataFrame:
    """Mean squared residual plus the weighted squared norms, by run."""
    data = residuals(triples, X, Z, cfg.d, keys).groupBy(*keys).agg(F.avg(F.col("e") * F.col("e")).alias("data"))
    squares = lambda f, p: f.groupBy(*keys).agg(F.sum(sum((F.col(c) * F.col(c) for c in cols(p, cfg.d)), F.lit(0.0))).alias(f"{p}2"))
    out = data.crossJoin(squares(X, "x")).crossJoin(squares(Z, "z")) if not keys else data.join(squares(X, "x"), list(keys)).join(squares(Z, "z"), list(keys))
    return out.select(*keys, (F.col("data") + cfg.lam_x * F.col("x2") + cfg.lam_z * F.col("z2")).alias("loss"))


def loss_dense(triples: DataFrame, X: DataFrame, Z: DataFrame, cfg: FitConfig) -> DataFrame:
    """The same through a bit for every cell, users times items: an invariant for small data."""
    cells = X.crossJoin(Z).join(triples, ["user_id", "item_id"], "left").withColumn("y", F.col("rating").isNotNull().cast("double"))
    e = F.coalesce("rating", F.lit(0.0)) - dot(cfg.d)
    return cells.agg((F.sum(F.col("y") * e * e) / F.sum("y")).alias("data"))


def user_gradient(res: DataFrame, d: int, keys: tuple[str, ...] = (), weight: Column | None = None) -> DataFrame:
    w = F.lit(-2.0) if weight is None else -2.0 * weight
    return res.groupBy(*keys, "user_id").agg(*(F.sum(w * F.col("e") * F.col(f"z{k}")).alias(f"g{k}") for k in range(d)))


def item_gradient(res: DataFrame, d: int, keys: tuple[str, ...] = (), weight: Column | None = None) -> DataFrame:
    w = F.lit(-2.0) if weight is None else -2.0 * weight
    return res.groupBy(*keys, "item_id").agg(*(F.sum(w * F.col("e") * F.col(f"x{k}")).alias(f"g{k}") for k in range(d)))


def projected(df: DataFrame, prefix: str, d: int, radius: float | None) -> DataFrame:
    """Vectors longer than ``radius`` are shortened to it."""
    if radius is None:
        return df
    size = F.sqrt(sum((F.col(c) * F.col(c) for c in cols(prefix, d)), F.lit(0.0)))
    shrink = F.least(F.lit(1.0), F.lit(radius) / F.greatest(size, F.lit(1e-300)))
    return df.select(*(c for c in df.columns if c not in cols(prefix, d)), *((F.col(c) * shrink).alias(c) for c in cols(prefix, d)))


def step(factors: DataFrame, grad: DataFrame, key: str, prefix: str, gamma: float, lam: float, cfg: FitConfig, keys: tuple[str, ...] = ()) -> DataFrame:
    """One descent step; an id without ratings is only drawn to zero."""
    joined = factors.join(grad, [*keys, key], "left")
    new = [(F.col(f"{prefix}{k}") - gamma * (F.coalesce(F.col(f"g{k}"), F.lit(0.0)) + 2 * lam * F.col(f"{prefix}{k}"))).alias(f"{prefix}{k}") for k in range(cfg.d)]
    return projected(joined.select(*keys, key, *new), prefix, cfg.d, cfg.max_norm)


def weighted(triples: DataFrame, cfg: FitConfig, keys: tuple[str, ...] = ()) -> DataFrame:
    """Triples with the divisors of both gradients: ratings, or items and users."""
    size = triples.groupBy(*keys).agg(F.count("*").alias("_n"), F.countDistinct("user_id").alias("_u"), F.countDistinct("item_id").alias("_i"))
    wu, wz = ("_n", "_n") if cfg.norm == "ratings" else ("_i", "_u")
    size = size.select(*keys, (1.0 / F.col(wu)).alias("wu"), (1.0 / F.col(wz)).alias("wz"))
    return triples.join(F.broadcast(size), list(keys)) if keys else triples.crossJoin(F.broadcast(size))  # a row for each run


def fit_plain(triples: DataFrame, cfg: FitConfig, keys: tuple[str, ...] = ()) -> FactorModel:
    """``cfg.rounds`` rounds over (keys, user_id, item_id, rating)."""
    scratch, by_user = Rounds(triples.sparkSession, "fit"), [*keys, "user_id"]
    data = scratch.keep(weighted(triples.select(*keys, "user_id", "item_id", "rating"), cfg, keys), "triples", by_user)
    X = scratch.keep(init_factors(data.select(*keys, "user_id").distinct(), "user_id", "x", cfg.d, cfg.seed), "x-0", by_user)
    Z = scratch.keep(init_factors(data.select(*keys, "item_id").distinct(), "item_id", "z", cfg.d, cfg.seed), "z-0")
    trace: list[dict] = []
    gamma: float | None = None
    for t in range(1, cfg.rounds + 1):
        seen = (trace[-2]["loss"], trace[-1]["loss"]) if len(trace) > 1 else None
        gamma = cfg.step.at(t, gamma, seen)
        for b in range(cfg.blocks or 1):
            part = data
            if cfg.blocks:  # one diagonal of user and item blocks at a time
                own = [F.pmod(hash_bits(cfg.seed, "block", F.col(c)), F.lit(cfg.blocks)) for c in ("user_id", "item_id")]
                part = data.where(own[0] == F.pmod(own[1] + b, F.lit(cfg.blocks)))
            res = residuals(part, X, Z, cfg.d, keys)
            newX = step(X, user_gradient(res, cfg.d, keys, F.col("wu")), "user_id", "x", gamma, cfg.lam_x, cfg, keys)
            if cfg.order == "alternate":
                newX = scratch.keep(newX, f"x-{t}-{b}", by_user)
                res = residuals(part, newX, Z, cfg.d, keys)
            newZ = step(Z, item_gradient(res, cfg.d, keys, F.col("wz")), "item_id", "z", gamma, cfg.lam_z, cfg, keys)
            newZ = scratch.keep(newZ, f"z-{t}-{b}")
            X, Z = (newX if cfg.order == "alternate" else scratch.keep(newX, f"x-{t}-{b}", by_user)), newZ
        if cfg.trace or cfg.tol is not None or cfg.step.kind == "bold":
            now = loss(data, X, Z, cfg, keys).agg(F.avg("loss")).first()[0]
            trace.append({"round": t, "loss": now, "gamma": gamma})
            if now is None or math.isnan(now) or now > 1e6:
                break
            if cfg.tol is not None and len(trace) > 1 and abs(trace[-2]["loss"] - now) < cfg.tol:
                break
        scratch.only("triples", f"x-{t}-{(cfg.blocks or 1) - 1}", f"z-{t}-{(cfg.blocks or 1) - 1}")
    scratch.drop("triples")
    return FactorModel(X, Z, trace, cfg)


def fold_in(ratings: DataFrame, Z: DataFrame, d: int, lam: float = 1e-2, method: str = "ridge", rounds: int = 50, gamma: float = 0.5) -> DataFrame:
    """User vectors for (user_id, item_id, rating) of new users, item vectors frozen.

    A user's ratings come down to sums of products, a row of fixed width; the small
    systems of many users are then solved in one call.
    """
    joined = ratings.join(Z, "item_id").select("user_id", "rating", *cols("z", d))
    pairs = [(i, j) for i in range(d) for j in range(i, d)]
    square = [F.sum(F.col(f"z{i}") * F.col(f"z{j}")).alias(f"a{i}_{j}") for i, j in pairs]
    sums = joined.groupBy("user_id").agg(F.count("*").cast("double").alias("n"), *square, *(F.sum(F.col("rating") * F.col(f"z{k}")).alias(f"b{k}") for k in range(d)))

    def solve(batches):
        import numpy as np

        for rows in batches:
            of = lambda c: rows.column(c).to_numpy(zero_copy_only=False)  # noqa: E731, B023
            n, b, a = of("n"), np.stack([of(f"b{k}") for k in range(d)], axis=1), np.zeros((rows.num_rows, d, d))
            for i, j in pairs:
                a[:, i, j] = a[:, j, i] = of(f"a{i}_{j}")
            if method == "ridge":
                x = np.linalg.solve(a + lam * n[:, None, None] * np.eye(d), b[..., None])[..., 0]
            else:
                x = np.zeros((rows.num_rows, d))
                for _ in range(rounds):
                    x = x - gamma * (-2 * (b - (a @ x[..., None])[..., 0]) / n[:, None] + 2 * lam * x)
            yield pa.RecordBatch.from_arrays([rows.column("user_id"), *(pa.array(x[:, k]) for k in range(d))], names=["user_id", *cols("x", d)])

    return sums.mapInArrow(solve, "user_id long, " + ", ".join(f"x{k} double" for k in range(d)))
