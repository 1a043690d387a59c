"""From visits to one rating per user and item, ids, and statistics of the matrix."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

RULES = ("majority", "latest", "most_private", "most_open")


def item_key(loc: Column, slot: Column) -> Column:
    return F.concat_ws("@", loc.cast("string"), slot.cast("string"))


def rating_of(rule: str) -> Column:
    """How contradicting answers become one; a tie hides."""
    if rule == "majority":
        return (F.avg("label") > 0.5).cast("double")
    if rule == "latest":
        return F.max_by(F.col("label"), F.struct("ts", "event_id")).cast("double")
    if rule in ("most_private", "most_open"):
        return (F.min if rule == "most_private" else F.max)("label").cast("double")
    raise ValueError(f"rule must be one of {RULES}")


def build(visits: DataFrame, loc: Column, slot: Column, rule: str = "majority", min_visits: int = 1) -> DataFrame:
    """``user_id, item, rating, visits``; rows with a null part of the key take no part."""
    keyed = visits.select("user_id", item_key(loc, slot).alias("item"), *(c for c in ("label", "ts", "event_id") if c in visits.columns)).where(loc.isNotNull() & slot.isNotNull() & F.col("label").isNotNull() & F.col("user_id").isNotNull())
    return keyed.groupBy("user_id", "item").agg(rating_of(rule).alias("rating"), F.count("*").alias("visits")).where(F.col("visits") >= min_visits)


def index(keys: DataFrame, column: str, method: str = "hash") -> DataFrame:
    """``column, id`` for its distinct values.

    ``rank``: dense, in key order, for small sets (one task). ``range``: dense, in key
    order, from range partitions and their offsets. ``hash``: 64-bit hashes, not dense.
    """
    distinct = keys.select(column).distinct()
    if method == "hash":
        return distinct.withColumn("id", F.xxhash64(column))
    if method == "rank":
        return distinct.withColumn("id", F.row_number().over(Window.orderBy(column)).cast("long") - 1)
    if method != "range":
        raise ValueError(f"unknown method {method}")
    placed = distinct.repartitionByRange(column).withColumn("_p", F.spark_partition_id()).cache()
    offsets = placed.groupBy("_p").count().withColumn("_o", F.coalesce(F.sum("count").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    ranked = placed.withColumn("_r", F.row_number().over(Window.partitionBy("_p").orderBy(column)).cast("long") - 1)
    return ranked.join(F.broadcast(offsets), "_p").select(column, (F.col("_r") + F.col("_o")).alias("id"))  # a row for each partition


def matrix_stats(triples: DataFrame, item: str = "item", approximate: bool = False) -> DataFrame:
    """Users, items, ratings, density and share of positive ratings in one row."""
    distinct = F.approx_count_distinct if approximate else F.countDistinct
    out = triples.agg(distinct("user_id").alias("users"), distinct(item).alias("items"), F.count("*").alias("ratings"), F.avg("rating").alias("positive"))
    return out.select("users", "items", "ratings", F.expr("try_divide(ratings, cast(users AS double) * items)").alias("density"), "positive")


def degrees(triples: DataFrame, side: str) -> DataFrame:
    return triples.groupBy(side).agg(F.count("*").alias("degree"))


#: Items that one row holds when a user's unrated ones are told.
ITEM_BLOCK = 4096


def unknown_cells(users: DataFrame, items: DataFrame, triples: DataFrame, item: str = "item") -> DataFrame:
    """Cells without a rating for the requested users: one row per user and unrated item.

    Items are dealt over blocks of about ITEM_BLOCK; each user meets each block's row
    and keeps what isn't among their own of that block. What comes out is users times
    items by nature; what is joined is not.
    """
    distinct = items.select(F.col(item)).distinct()
    n = max(1, -(-distinct.count() // ITEM_BLOCK))
    block = F.pmod(F.xxhash64(item), F.lit(n)).alias("_block")
    blocks = distinct.groupBy(block).agg(F.collect_list(item).alias("_all"))
    rated = triples.groupBy("user_id", block).agg(F.collect_set(item).alias("_own"))
    asked = users.select("user_id").distinct().crossJoin(blocks).join(rated, ["user_id", "_block"], "left")
    return asked.select("user_id", F.explode(F.array_except("_all", F.coalesce("_own", F.array().cast(blocks.schema["_all"].dataType)))).alias(item))
