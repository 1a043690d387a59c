"""Scores, thresholds and recommendations from a pair of factor tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .factorization import cols, dot


def score(pairs: DataFrame, X: DataFrame, Z: DataFrame, d: int, keys: tuple[str, ...] = ()) -> DataFrame:
    return pairs.join(X, [*keys, "user_id"]).join(Z, [*keys, "item_id"]).withColumn("score", dot(d)).drop(*cols("x", d), *cols("z", d))


def mean_threshold(X: DataFrame, Z: DataFrame, d: int, keys: tuple[str, ...] = (), scope: str = "all_cells", observed: DataFrame | None = None, fixed: float = 0.5) -> DataFrame:
    """``threshold`` by run, or by run and user.

    The mean of all products of a full grid is the product of the mean vectors, so the
    grid is never built.
    """
    mean = lambda f, p: f.groupBy(*keys).agg(*(F.avg(c).alias(c) for c in cols(p, d)))
    if scope == "fixed":
        base = X.select(*keys).distinct() if keys else X.sparkSession.range(1).select()
        return base.select(*keys, F.lit(float(fixed)).alias("threshold"))
    if scope == "observed":
        if observed is None:
            raise ValueError("the observed cells are needed")
        return score(observed, X, Z, d, keys).groupBy(*keys).agg(F.avg("score").alias("threshold"))
    z = mean(Z, "z")
    if scope == "per_user":
        joined = X.join(F.broadcast(z), list(keys)) if keys else X.crossJoin(F.broadcast(z))
        return joined.select(*keys, "user_id", dot(d).alias("threshold"))
    if scope != "all_cells":
        raise ValueError(f"unknown scope {scope}")
    x = mean(X, "x")
    return (x.join(z, list(keys)) if keys else x.crossJoin(z)).select(*keys, dot(d).alias("threshold"))


def decide(scored: DataFrame, threshold: DataFrame) -> DataFrame:
    """``decision`` 1 above the threshold; a tie hides."""
    on = [c for c in threshold.columns if c != "threshold"]
    joined = scored.join(F.broadcast(threshold) if "user_id" not in on else threshold, on) if on else scored.crossJoin(F.broadcast(threshold))
    return joined.withColumn("decision", (F.col("score") > F.col("threshold")).cast("int")).drop("threshold")


def recommend(cells: DataFrame, X: DataFrame, Z: DataFrame, d: int, scope: str = "all_cells", observed: DataFrame | None = None) -> DataFrame:
    return decide(score(cells, X, Z, d), mean_threshold(X, Z, d, scope=scope, observed=observed))


def top_k(scored: DataFrame, k: int, tie: str = "item_id") -> DataFrame:
    best = Window.partitionBy("user_id").orderBy(F.desc("score"), tie)
    return scored.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
