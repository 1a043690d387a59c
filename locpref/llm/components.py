"""Connected components of an edge table by alternating star contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, hot_floor, met


def _pull(edges: DataFrame, large: bool) -> DataFrame:
    """One contraction: neighbours of a node are hung on the least of them.

    Large: the greater neighbours move, seen from either end. Small: the lesser ones
    and the node itself move.
    """
    if large:
        seen = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    else:
        seen = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = seen.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
    moved = seen.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"), F.col("u").alias("w"))
    if large:
        return moved.where("u > w").select("u", "v")
    own = least.select("u", F.col("m").alias("v"))
    return moved.select("u", "v").unionByName(own).where("u <> v").distinct()


def components(edges: DataFrame, scratch: Scratch, name: str = "cc", most_rounds: int = 60) -> DataFrame:
    """``node, component``: the least id reachable, for every node that has an edge.

    Stops when a round changes nothing; rounds grow with the logarithm of the paths.
    """
    now = scratch.keep(edges.select("u", "v").where("u <> v").distinct(), f"{name}-0")
    sign = None
    for k in range(1, most_rounds):
        now = scratch.keep(_pull(_pull(now, True), False), f"{name}-{k}")
        scratch.drop(f"{name}-{k - 1}")
        mark = now.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v")), F.bit_xor(F.xxhash64("v", "u"))).first()
        if mark == sign:
            break
        sign = mark
    else:
        raise RuntimeError("components didn't settle")
    leaves = now.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return leaves.unionByName(leaves.select(F.col("component").alias("node"), "component").distinct())


def forest_components(parents: DataFrame, scratch: Scratch, name: str = "forest", most_rounds: int = 60) -> DataFrame:
    """The same for a forest (u is the one parent of v) by pointer jumping: log of the depth rounds."""
    now = parents.select("v", "u").distinct()
    for k in range(most_rounds):
        above = now.select(F.col("v").alias("u"), F.col("u").alias("top"))
        jumped = now.join(above, "u", "left").select("v", F.coalesce("top", "u").alias("u"), F.col("top").isNotNull().alias("moved"))
        jumped = scratch.keep(jumped, f"{name}-{k}")
        if k:
            scratch.drop(f"{name}-{k - 1}")
        now = jumped.select("v", "u")
        if jumped.where("moved").isEmpty():
            break
    else:
        raise RuntimeError("the forest has a cycle")
    roots = now.select(F.col("u").alias("v"), "u").distinct()
    nodes = now.unionByName(roots)
    least = scratch.keep(nodes.groupBy("u").agg(F.min("v").alias("component"), F.count("*").alias("c")), f"{name}-least")
    return met(nodes, least, ["u"], F.col("c") > hot_floor(now.count())).select(F.col("v").alias("node"), "component")
