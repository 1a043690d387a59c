"""Randomised response, clipping, Laplace noise, budgets and their audit.

One bit: with probability p a fair coin replaces it. The worst likelihood ratio is
(2 - p) / p, so p = 2 / (1 + e^eps) gives eps. A clipped vector has L1 norm C at most;
two of them differ by 2C, so each coordinate gets Laplace noise of scale 2C / eps.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T


def flip_probability(eps: float) -> float:
    if eps < 0:
        raise ValueError("eps must not be negative")
    return 2 / (1 + math.exp(eps)) if eps < 700 else 0.0


def flip_probability_column(eps: Column) -> Column:
    return 2.0 / (1.0 + F.exp(eps))


def randomize_bit(y: Column, p: Column | float, u1: Column, u2: Column) -> Column:
    p = p if isinstance(p, Column) else F.lit(float(p))
    return F.when(u1 < p, (u2 < 0.5).cast("int")).otherwise(y.cast("int"))


def bit_weight(bit: Column, p: Column | float) -> Column:
    """Unbiased for the true bit; p = 1 carries nothing and has no estimate."""
    if not isinstance(p, Column):
        if p >= 1:
            raise ValueError("p = 1 leaves nothing to estimate from")
        p = F.lit(float(p))
    return (bit - p / 2) / (1 - p)


def norm(g: list[Column], kind: str) -> Column:
    if kind == "l1":
        return sum((F.abs(x) for x in g[1:]), F.abs(g[0]))
    if kind == "l2":
        return F.sqrt(sum((x * x for x in g[1:]), g[0] * g[0]))
    raise ValueError(f"unknown norm {kind}")


def clip(g: list[Column], bound: float, kind: str = "l1") -> list[Column]:
    """Vectors inside the ball of radius ``bound``; ``coordinate`` cuts each component."""
    if kind == "coordinate":
        return [F.greatest(F.lit(-bound), F.least(F.lit(bound), x)) for x in g]
    scale = F.least(F.lit(1.0), F.lit(float(bound)) / F.greatest(norm(g, kind), F.lit(1e-300)))
    return [x * scale for x in g]


def laplace(u: Column, scale: Column | float) -> Column:
    """Inverse distribution function; u is kept off 0 and 1."""
    v = F.greatest(F.lit(2.0**-53), F.least(F.lit(1 - 2.0**-53), u)) - 0.5
    return -scale * F.signum(v) * F.log(1.0 - 2.0 * F.abs(v))


@F.pandas_udf(T.DoubleType())
def _entropy(marker: pd.Series) -> pd.Series:
    import os

    import numpy as np

    raw = np.frombuffer(os.urandom(8 * len(marker)), np.uint64) >> np.uint64(11)
    return pd.Series((raw.astype(float) + 0.5) / 2**53)


#: Never folded, merged or moved: every use is a draw of its own.
_entropy = _entropy.asNondeterministic()


def secure_uniform(purpose: str, *parts: Column) -> Column:
    """A uniform draw from the system's entropy: not reproducible. Write a report before it is read twice."""
    return _entropy(F.xxhash64(F.lit(purpose), *parts))


def laplace_secure(scale: Column | float, marker: Column, purpose: str = "lap") -> Column:
    return laplace(secure_uniform(purpose, marker), scale)


@dataclass(frozen=True)
class Budget:
    """How eps is spent over rounds, items and the kinds of releases.

    ``per_report``: eps for each report, the weakest reading. ``per_item``: eps for
    all rounds of an item, while the user vector is frozen. ``per_user``: eps for all
    that a user ever sends, which holds for arbitrary inputs. Bits and item gradients
    are sent for each item, a user gradient once a round; ``user_share`` of eps is for
    the latter, and the rest is split by ``bit_share``.
    """

    policy: str
    eps: float
    bit_share: float = 0.5
    rounds: int = 1
    items: int = 1
    permanent_bits: bool = False
    user_share: float = 0.0

    def __post_init__(self) -> None:
        if self.policy not in ("per_report", "per_item", "per_user"):
            raise ValueError(f"unknown policy {self.policy}")
        if self.eps <= 0 or not 0 <= self.bit_share <= 1 or not 0 <= self.user_share < 1:
            raise ValueError("eps must be positive, bit_share and user_share shares")

    def per_round(self) -> tuple[float, float]:
        """eps of one bit and of one item gradient in one round."""
        rest = (1 - self.user_share) * self.eps
        rounds = {"per_report": 1, "per_item": self.rounds, "per_user": self.rounds * self.items}[self.policy]
        bits = 1 if self.permanent_bits else self.rounds
        bits = {"per_report": 1, "per_item": bits, "per_user": bits * self.items}[self.policy]
        return self.bit_share * rest / bits, (1 - self.bit_share) * rest / rounds

    def user_gradient(self) -> float:
        """eps of the one user gradient of a round."""
        return self.user_share * self.eps / (1 if self.policy == "per_report" else self.rounds)

    def releases(self) -> list[tuple[str, float, bool]]:
        """Mechanism, what a round spends on it under the policy, and whether only the first round does."""
        bit, grad = self.per_round()
        times = self.items if self.policy == "per_user" else 1
        out = [("bit", bit * times, self.permanent_bits), ("gradient", grad * times, False)]
        return out + ([("user_gradient", self.user_gradient(), False)] if self.user_share else [])


def spending(users: DataFrame, budget: Budget) -> DataFrame:
    """``user_id, round, mechanism, eps_spent``: what every user spends in every round."""
    rounds = users.sparkSession.range(1, budget.rounds + 1).select(F.col("id").cast("int").alias("round"))
    spent = [F.struct(F.lit(name).alias("mechanism"), F.when(F.lit(once) & (F.col("round") > 1), F.lit(0.0)).otherwise(F.lit(x)).alias("eps_spent")) for name, x, once in budget.releases()]
    rows = users.select("user_id").crossJoin(F.broadcast(rounds))  # a few rounds
    return rows.select("user_id", "round", F.explode(F.array(*spent)).alias("x")).select("user_id", "round", "x.*")


def ledger(users: DataFrame, budget: Budget) -> DataFrame:
    """What every user has spent after every round, by mechanism, under sequential composition."""
    so_far = Window.partitionBy("user_id").orderBy("round", "mechanism").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return spending(users, budget).withColumn("eps_total", F.sum("eps_spent").over(so_far))


def totals(users: DataFrame, budget: Budget) -> DataFrame:
    """``user_id, eps_total, releases``: the ledger's last line for every user, by a sum that is combined before the shuffle."""
    return spending(users, budget).groupBy("user_id").agg(F.sum("eps_spent").alias("eps_total"), F.size(F.collect_set("mechanism")).cast("long").alias("releases"))


def audit_levels(levels: DataFrame, bound: float = 1.0, steps: int = 40) -> DataFrame:
    """Worst likelihood ratios of bit and Laplace noise against e^eps (``levels``: eps), on a grid of outputs."""
    grid = levels.crossJoin(F.broadcast(levels.sparkSession.range(-steps, steps + 1).select((F.col("id") * bound / 10).alias("out"))))  # 2 steps + 1 rows
    p = flip_probability_column(F.col("eps"))
    scale = 2 * bound / F.col("eps")
    ratio = F.exp((F.abs(F.col("out") + bound) - F.abs(F.col("out") - bound)) / scale)
    return grid.groupBy("eps").agg(F.max(((2 - p) / p) / F.exp("eps")).alias("bit_ratio"), F.max(ratio / F.exp("eps")).alias("laplace_ratio"))


def audit(spark: SparkSession, eps_grid: list[float], bound: float = 1.0, steps: int = 40) -> DataFrame:
    return audit_levels(spark.createDataFrame([(float(e),) for e in eps_grid], "eps double"), bound, steps)
