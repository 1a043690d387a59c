"""Neighbour influence and leakage over time."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def neighbour_smooth(scores: DataFrame, neighbours: DataFrame, alpha: float) -> DataFrame:
    """Scores by (user_id, loc) drawn by alpha to the mean of their neighbours (loc, near)."""
    near = neighbours.join(scores.withColumnsRenamed({"loc": "near", "score": "other"}), "near").groupBy("user_id", "loc").agg(F.avg("other").alias("other"))
    out = scores.join(near, ["user_id", "loc"], "left")
    return out.withColumn("score", (1 - alpha) * F.col("score") + alpha * F.coalesce("other", "score")).drop("other")


def transitions(visits: DataFrame, hours: int) -> DataFrame:
    """Probabilities ``slot, next_slot, p`` between a user's visits in order of time."""
    slot = F.floor(F.hour("ts") / hours).cast("int")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    steps = visits.withColumn("slot", slot).withColumn("next_slot", F.lead("slot").over(w)).where("next_slot is not null").groupBy("slot", "next_slot").agg(F.count("*").alias("n"))
    return steps.withColumn("p", F.col("n") / F.sum("n").over(Window.partitionBy("slot"))).drop("n")


def temporal_leakage(eps_series: list[float], matrix: list[list[float]] | None = None) -> list[float]:
    """Backward leakage after each release when states follow a Markov matrix.

    Without a matrix the worst case, the running sum. With one, the leakage carried to
    the next step is the largest log ratio over pairs of rows and subsets of columns;
    the best subset takes columns by ratio, so it is found by sorting.
    """
    out, carried = [], 0.0
    for eps in eps_series:
        out.append(carried + eps)
        if matrix is None:
            carried = out[-1]
            continue
        worst, e = 0.0, math.exp(out[-1]) - 1
        for a in matrix:
            for b in matrix:
                q = d = 0.0
                for x, y in sorted(zip(a, b, strict=True), key=lambda v: -(v[0] / v[1] if v[1] else math.inf)):
                    if (x or y) and (y == 0 or math.log(((q + x) * e + 1) / ((d + y) * e + 1)) >= math.log((q * e + 1) / (d * e + 1))):
                        q, d = q + x, d + y
                worst = max(worst, math.log((q * e + 1) / (d * e + 1)))
        carried = worst
    return out
