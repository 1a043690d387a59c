"""Accuracy, privacy and traffic measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_RATES = {
    "fpr": "try_divide(fp, cast(fp + tn AS double))",
    "recall": "try_divide(tp, cast(tp + fn AS double))",
    "reconstruction": "try_divide(tp + tn, cast(tp + fp + tn + fn AS double))",
    "precision": "try_divide(tp, cast(tp + fp AS double))",
    "f1": "try_divide(2 * tp, cast(2 * tp + fp + fn AS double))",
    "balanced": "(try_divide(tp, cast(tp + fn AS double)) + try_divide(tn, cast(tn + fp AS double))) / 2",
}


def confusion(scored: DataFrame, by: tuple[str, ...] = (), truth: str = "truth") -> DataFrame:
    """Counts of decisions against the truth; publishing is the positive side."""
    t, p = F.col(truth) == 1, F.col("decision") == 1
    return scored.groupBy(*by).agg(F.count_if(t & p).alias("tp"), F.count_if(~t & p).alias("fp"), F.count_if(~t & ~p).alias("tn"), F.count_if(t & ~p).alias("fn"))


def rates(counts: DataFrame, *names: str) -> DataFrame:
    """Ratios of confusion counts; null where nothing stands below the line."""
    return counts.select("*", *(F.expr(_RATES[n]).alias(n) for n in names or _RATES))


def closeness(scored: DataFrame, by: tuple[str, ...] = (), truth: str = "rating") -> DataFrame:
    e = F.col(truth) - F.col("score")
    return scored.groupBy(*by).agg(F.sqrt(F.avg(e * e)).alias("rmse"), F.avg(F.abs(e)).alias("mae"))


def summarise(rows: DataFrame, by: tuple[str, ...], measures: tuple[str, ...]) -> DataFrame:
    """Mean, standard deviation and half width of a 95 % interval over folds and repetitions."""
    out = []
    for m in measures:
        out += [F.avg(m).alias(f"{m}_mean"), F.stddev_samp(m).alias(f"{m}_sd"), (1.96 * F.stddev_samp(m) / F.sqrt(F.count(m))).alias(f"{m}_half")]
    return rows.groupBy(*by).agg(F.count("*").alias("n"), *out)


def gap(rows: DataFrame, by: tuple[str, ...], measure: str, a: str = "private", b: str = "plain") -> DataFrame:
    """Measure of method a minus that of method b for every setting."""
    wide = rows.groupBy(*by).pivot("method", [a, b]).agg(F.avg(measure))
    return wide.withColumn("gap", F.col(a) - F.col(b))


def traffic(spark: SparkSession, n: int, m: int, d: int, ratings: int, rounds: int) -> DataFrame:
    """Bytes a round sends down and up: whole factors down, then gradients or reports up (8-byte numbers)."""
    kinds = [("plain", 8 * d * (n + m), 8 * (d + 2) * ratings), ("private", 8 * d * m * n, (8 * d + 1) * n * m), ("sampled_10", 8 * d * m * n, (8 * d + 1) * n * min(10, m))]
    return spark.createDataFrame([(k, down, up, (down + up) * rounds) for k, down, up in kinds], "protocol string, bytes_down long, bytes_up long, bytes_total long")


def estimator_error(estimates: DataFrame, truth: str, by: tuple[str, ...]) -> DataFrame:
    """Bias and variance of an estimate over repetitions."""
    return estimates.groupBy(*by).agg((F.avg("estimate") - F.avg(truth)).alias("bias"), F.var_samp("estimate").alias("variance"), F.count("*").alias("n"))
