"""Labelled data: a small survey carried over to many visits, and planted truths."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import gaussian, hash_bits, uniform


def categories_of(visits: DataFrame) -> DataFrame:
    """``category, k`` numbered in order: a handful of rows."""
    return visits.select("category").distinct().withColumn("k", F.row_number().over(Window.orderBy("category")) - 1)


def mapped_survey(survey: DataFrame, visits: DataFrame, seed: int = 42) -> DataFrame:
    """Survey categories replaced by visit categories, by hash."""
    kinds = categories_of(visits)
    n = kinds.agg(F.count("*").alias("n"))
    keyed = survey.crossJoin(F.broadcast(n)).withColumn("k", F.pmod(hash_bits(seed, "category", F.col("category")), F.col("n")).cast("int"))
    return keyed.drop("category", "n").join(F.broadcast(kinds), "k").drop("k")


def survey_rates(survey: DataFrame) -> DataFrame:
    return survey.groupBy("category", "slot").agg(F.avg("answer").alias("rate"), F.count("*").alias("answers"))


def transfer_rate(survey: DataFrame, visits: DataFrame, seed: int = 42) -> DataFrame:
    """Visits (with ``slot``) labelled by the survey's share for their category and slot.

    Back-off: category and slot, then category, then all answers. The draw is fixed by
    the event.
    """
    fine = survey.groupBy("category", "slot").agg(F.avg("answer").alias("r2"))
    by_category = survey.groupBy("category").agg(F.avg("answer").alias("r1"))
    overall = survey.agg(F.avg("answer").alias("r0"))
    out = visits.drop("label").join(F.broadcast(fine), ["category", "slot"], "left").join(F.broadcast(by_category), "category", "left").crossJoin(F.broadcast(overall))
    out = out.withColumn("rate", F.coalesce("r2", "r1", "r0"))
    return out.withColumn("label", (uniform(seed, "transfer", F.col("event_id")) < F.col("rate")).cast("int")).drop("r0", "r1", "r2")


def archetypes(survey: DataFrame, visits: DataFrame, assign: str = "hash", seed: int = 42) -> DataFrame:
    """``user_id, respondent``: by hash, or the respondent with the nearest category profile (cosine)."""
    people = survey.select("respondent").distinct().withColumn("r", F.row_number().over(Window.orderBy("respondent")) - 1)
    if assign == "hash":
        n = people.agg(F.count("*").alias("n"))
        users = visits.select("user_id").distinct().crossJoin(F.broadcast(n)).withColumn("r", F.pmod(hash_bits(seed, "archetype", F.col("user_id")), F.col("n")).cast("int"))
        return users.join(F.broadcast(people), "r").select("user_id", "respondent")
    if assign != "cosine":
        raise ValueError(f"unknown assignment {assign}")
    own = visits.groupBy("user_id", "category").agg(F.count("*").cast("double").alias("n"))
    theirs = survey.groupBy("respondent", "category").agg(F.count("*").cast("double").alias("m"))
    length = theirs.groupBy("respondent").agg(F.sqrt(F.sum(F.col("m") * F.col("m"))).alias("l"))
    dots = own.join(F.broadcast(theirs), "category").groupBy("user_id", "respondent").agg(F.sum(F.col("n") * F.col("m")).alias("dot"))  # a survey is small by definition
    near = dots.join(F.broadcast(length), "respondent").groupBy("user_id").agg(F.max_by("respondent", F.struct(F.round(F.col("dot") / F.col("l"), 9), "respondent")).alias("respondent"))
    return near


def transfer_archetype(survey: DataFrame, visits: DataFrame, assign: str = "hash", seed: int = 42) -> DataFrame:
    """Visits labelled with their archetype's majority answer for category and slot, else null."""
    answers = survey.groupBy("respondent", "category", "slot").agg((F.avg("answer") > 0.5).cast("int").alias("label"))
    return visits.drop("label").join(archetypes(survey, visits, assign, seed), "user_id", "left").join(F.broadcast(answers), ["respondent", "category", "slot"], "left")


def integrate(survey: DataFrame, visits: DataFrame, mode: str = "hybrid", assign: str = "hash", seed: int = 42) -> DataFrame:
    """Labelled visits by rate, archetype or both (the archetype's answer first)."""
    if mode == "rate":
        return transfer_rate(survey, visits, seed)
    own = transfer_archetype(survey, visits, assign, seed)
    if mode == "archetype":
        return own
    if mode != "hybrid":
        raise ValueError(f"unknown mode {mode}")
    rated = transfer_rate(survey, own.withColumnRenamed("label", "own").withColumn("label", F.lit(0)), seed)
    return rated.withColumn("label", F.coalesce("own", "label")).drop("own")


def planted_vectors(ids: DataFrame, key: str, side: str, rank: int = 3, seed: int = 42) -> DataFrame:
    """``key, _x0..`` (or ``_z0..``): a planted vector for each distinct value of a column, to be drawn once for all its cells."""
    return ids.select(key).distinct().select(key, *(gaussian(seed, f"planted_{side}", F.col(key), F.lit(k)).alias(f"_{side}{k}") for k in range(rank)))


def _planted_pairs(user: Column, item: Column, rank: int, seed: int, drawn: bool) -> list[tuple[Column, Column]]:
    if drawn:
        return [(F.col(f"_x{k}"), F.col(f"_z{k}")) for k in range(rank)]
    return [(gaussian(seed, "planted_x", user, F.lit(k)), gaussian(seed, "planted_z", item, F.lit(k))) for k in range(rank)]


def planted(cells: DataFrame, rank: int = 3, offset: float = 0.3, flip: float = 0.05, seed: int = 42, drawn: bool = False) -> DataFrame:
    """``truth`` of low rank for (user_id, item) cells, and ``rating``, which differs in a share ``flip`` of them. With ``drawn`` the cells have ``planted_vectors`` of both sides."""
    parts = [x * z for x, z in _planted_pairs(F.col("user_id"), F.col("item"), rank, seed, drawn)]
    truth = (sum(parts[1:], parts[0]) + offset > 0).cast("int")
    out = cells.withColumn("truth", truth)
    flipped = uniform(seed, "flip", F.col("user_id"), F.col("item")) < flip
    return out.withColumn("rating", F.when(flipped, 1 - F.col("truth")).otherwise(F.col("truth")).cast("double"))


def planted_hourly(visits: DataFrame, key: Column, rank: int = 3, offset: float = 0.3, flip: float = 0.05, swing: float = 1.5, seed: int = 42, drawn: bool = False) -> DataFrame:
    """Visits with a label from a truth that changes smoothly over the day's hours; ``drawn`` as in ``planted``."""
    hour, user = F.hour("ts"), F.col("user_id")
    angle = 2 * math.pi * hour / 24
    wave = [F.cos(angle), F.sin(angle)]
    parts = [x * (z + (swing * wave[k] if k < 2 else F.lit(0.0))) for k, (x, z) in enumerate(_planted_pairs(user, key, rank, seed, drawn))]
    truth = (sum(parts[1:], parts[0]) + offset > 0).cast("int")
    flipped = uniform(seed, "flip_hour", user, key, hour) < flip
    return visits.withColumn("truth", truth).withColumn("label", F.when(flipped, 1 - F.col("truth")).otherwise(F.col("truth")).cast("int"))


def describe(visits: DataFrame) -> DataFrame:
    """Users, records, places and period of a carrier."""
    return visits.agg(F.countDistinct("user_id").alias("users"), F.count("*").alias("records"), F.countDistinct("place").alias("places"), F.min("ts").alias("first_ts"), F.max("ts").alias("last_ts"))
