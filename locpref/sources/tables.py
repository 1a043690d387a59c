"""Readers that turn the given tables into visits, and interchange formats."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A visit whose value is this much or more counts as publishable in the raw labels.
OPEN_VALUE = 35


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def event_visits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``user_id, event_id, ts, category, place, label`` from events."""
    e = table(spark, sf_dir, "events")
    place = F.get_json_object("props", "$.k").cast("int")
    return e.select("user_id", "event_id", "ts", F.col("event_type").alias("category"), place.alias("place"), (F.col("value") >= OPEN_VALUE).cast("int").alias("label"))


def order_visits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sparse carrier: customers at suppliers, with area, region and category."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_returnflag")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    nation = table(spark, sf_dir, "nation").join(F.broadcast(table(spark, sf_dir, "region")), F.expr("n_regionkey = r_regionkey"))  # 25 and 5 rows
    where = table(spark, sf_dir, "supplier").join(F.broadcast(nation), F.expr("s_nationkey = n_nationkey")).select("s_suppkey", "n_name", "r_name")
    part = table(spark, sf_dir, "part").select("p_partkey", "p_type")
    out = line.join(orders, F.expr("l_orderkey = o_orderkey")).join(where, F.expr("l_suppkey = s_suppkey")).join(part, F.expr("l_partkey = p_partkey"))
    event = F.col("l_orderkey") * 10 + F.col("l_linenumber")
    return out.select(F.col("o_custkey").alias("user_id"), event.alias("event_id"), F.col("o_orderdate").alias("ts"), F.col("p_type").alias("category"), F.col("l_suppkey").alias("place"), F.col("n_name").alias("area"), F.col("r_name").alias("region"), (F.col("l_returnflag") != "R").cast("int").alias("label"))


def survey_answers(spark: SparkSession, sf_dir: str, hours: int = 6) -> DataFrame:
    """A small survey: ``respondent, category, slot, answer`` from labelled documents."""
    answers = table(spark, sf_dir, "labels").join(table(spark, sf_dir, "documents").select("doc_id", "lang", "source"), "doc_id")
    return answers.select(F.col("source").alias("respondent"), F.col("lang").alias("category"), F.pmod("doc_id", F.lit(24 // hours)).cast("int").alias("slot"), F.col("quality").cast("int").alias("answer"))


def write_triples(triples: DataFrame, path: str, kind: str = "parquet") -> None:
    """Export in a format that other tools read: parquet, orc, json or csv."""
    w = triples.write.mode("overwrite")
    w.option("header", True).csv(path) if kind == "csv" else w.format(kind).save(path)


def read_triples(spark: SparkSession, path: str, kind: str = "parquet", schema: str = "user_id long, item_id long, rating double") -> DataFrame:
    r = spark.read.schema(schema)
    return r.option("header", True).csv(path) if kind == "csv" else r.format(kind).load(path)


def save_model(x: DataFrame, z: DataFrame, config: dict, path: str) -> None:
    """Factors as Parquet and the configuration as one JSON line; the config comes last and marks a whole model."""
    x.write.mode("overwrite").parquet(f"{path}/X")
    z.write.mode("overwrite").parquet(f"{path}/Z")
    x.sparkSession.createDataFrame([(json.dumps(config),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/config")


def load_model(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame, dict]:
    config = json.loads(spark.read.text(f"{path}/config").first().value)
    return spark.read.parquet(f"{path}/X"), spark.read.parquet(f"{path}/Z"), config
