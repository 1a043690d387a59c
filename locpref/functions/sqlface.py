"""The functions for SQL users: temporary SQL functions, an aggregate and a table function."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

SQL_FUNCTIONS = {
    "time_slot": "(ts TIMESTAMP, hours INT) RETURNS INT RETURN CAST(floor(hour(ts) / hours) AS INT)",
    "flip_probability": "(eps DOUBLE) RETURNS DOUBLE RETURN 2 / (1 + exp(eps))",
    "bit_weight": "(bit INT, p DOUBLE) RETURNS DOUBLE RETURN (bit - p / 2) / (1 - p)",
    "dot": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), CAST(0 AS DOUBLE), (s, x) -> s + x)",
}


def mean_vector():
    """Aggregate for wide vectors: their mean, by coordinate."""

    @F.pandas_udf(T.ArrayType(T.DoubleType()))
    def mean(v: pd.Series) -> list:
        import numpy as np

        held = v.dropna()
        return np.stack(held.to_list()).astype(float).mean(axis=0).tolist() if len(held) else None

    return mean


class TimeLadder:
    """Keys of one hour on every granularity, finest first."""

    def eval(self, hour: int):
        for width in (1, 2, 3, 4, 6, 8, 12, 24):
            yield width, hour // width


def register(spark: SparkSession) -> None:
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udf.register("mean_vector", mean_vector())
    spark.udtf.register("time_ladder", F.udtf(TimeLadder, returnType="width int, slot int"))
