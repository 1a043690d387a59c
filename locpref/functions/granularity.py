"""How finely time and place are told apart: keys from time stamps and locations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WIDTHS = (1, 2, 3, 4, 6, 8, 12, 24)
MONTH_WIDTHS = (1, 2, 3, 4, 6, 12)
# Names of the parts of a day. Ours: four hours each, the first from six.
DAY_PARTS = ("Morning", "Noon", "Afternoon", "Evening", "Night", "Midnight")


def time_slot(ts: Column, hours: int) -> Column:
    if hours not in WIDTHS:
        raise ValueError(f"a slot of {hours} hours doesn't divide a day; use one of {WIDTHS}")
    return F.floor(F.hour(ts) / hours).cast("int")


def day_part(ts: Column) -> Column:
    return F.element_at(F.array(*map(F.lit, DAY_PARTS)), (F.floor(F.pmod(F.hour(ts) + 18, F.lit(24)) / 4) + 1).cast("int"))


def day_kind(ts: Column) -> Column:
    return F.when(F.weekday(ts) < 5, "Weekday").otherwise("Weekend")


def day_name(ts: Column) -> Column:
    return F.date_format(ts, "EEEE")


def month_of(ts: Column) -> Column:
    return F.month(ts)


def time_key(ts: Column, parts: tuple[str, ...]) -> Column:
    """Several parts in one key, such as ``("month", "kind", "part")``."""
    made = {"part": day_part, "kind": day_kind, "name": day_name, "month": lambda t: month_of(t).cast("string")}
    return F.concat_ws(":", *(made[p](ts) for p in parts))


def calendar_slot(ts: Column, hours: int) -> Column:
    """Start of the slot on the calendar, not folded by day."""
    if hours not in WIDTHS:
        raise ValueError(f"a slot of {hours} hours doesn't divide a day")
    return F.window(ts, f"{hours} hours")["start"]


def month_slot(date: Column, months: int) -> Column:
    if months not in MONTH_WIDTHS:
        raise ValueError(f"{months} months don't divide a year")
    return F.floor((F.month(date) - 1) / months).cast("int")


def grid_cell(lat: Column, lon: Column, degrees: float) -> Column:
    return F.struct(F.floor(lat / degrees).cast("int").alias("lat_bin"), F.floor(lon / degrees).cast("int").alias("lon_bin"))


def location_key(kind: str) -> Column:
    """Over columns ``category``, ``area``, ``place``: one of them, or category and area."""
    if kind == "category_area":
        return F.concat_ws(":", "category", "area")
    if kind == "category_place":
        return F.concat_ws(":", "category", F.col("place").cast("string"))
    if kind not in ("category", "area", "place"):
        raise ValueError(f"unknown location key {kind}")
    return F.col(kind).cast("string")


def rollup_location(visits: DataFrame, ladder: tuple[str, ...] = ("region", "area", "place")) -> DataFrame:
    """Visits and publishable share on every level of the ladder, coarse to fine."""
    out = visits.rollup(*ladder).agg(F.grouping_id().alias("level"), F.count("*").alias("visits"), F.sum("label").cast("long").alias("open"))
    return out.withColumn("level", F.col("level").cast("long"))
