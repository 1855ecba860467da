"""Measures over ``results``: one row per query (or plan node), estimator and sample size."""

from __future__ import annotations

import itertools

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

RESULT = ["query_id", "estimator", "size", "sigma", "sigma_true"]


def abs_error() -> Column:
    return F.abs(F.col("sigma") - F.col("sigma_true"))


def percent_error() -> Column:
    """100 |p - true| / true; with an empty truth 0 if nothing was predicted, else undefined (NULL)."""
    return F.when(F.col("sigma_true") > 0, 100 * abs_error() / F.col("sigma_true")).when(F.col("sigma") == 0, 0.0)


def q_error() -> Column:
    low, high = F.least("sigma", "sigma_true"), F.greatest("sigma", "sigma_true")
    return F.when(low > 0, high / low).when(high == 0, 1.0)


def with_errors(results: DataFrame, eps: float) -> DataFrame:
    return results.withColumn("abs_err", abs_error()).withColumn("pct_err", percent_error()).withColumn("within", abs_error() <= eps)


def violations(results: DataFrame, eps: float, by: tuple[str, ...] = ("estimator", "size")) -> DataFrame:
    """``estimator, size, queries, violations``."""
    return results.groupBy(*by).agg(F.count("*").alias("queries"), F.count_if(abs_error() > eps).alias("violations"))


def error_curve(results: DataFrame, by: tuple[str, ...] = ("estimator", "size")) -> DataFrame:
    """Mean and both standard deviations of the percent error, with how many were undefined, per estimator and size."""
    p = percent_error()
    return results.groupBy(*by).agg(
        F.round(F.avg(p), 6).alias("mean_pct"), F.round(F.stddev_pop(p), 6).alias("sd_pop_pct"), F.round(F.stddev_samp(p), 6).alias("sd_samp_pct"), F.count_if(p.isNull()).alias("undefined"), F.count("*").alias("queries")
    )


def win_count(results: DataFrame, challenger: str, champion: str) -> DataFrame:
    """Queries for which the challenger is strictly closer than the champion, per size of the champion."""
    a = results.where(F.col("estimator") == challenger).select("query_id", abs_error().alias("e1"))
    b = results.where(F.col("estimator") == champion).select("query_id", "size", abs_error().alias("e2"))
    return a.join(b, "query_id").groupBy("size").agg(F.count_if(F.col("e1") < F.col("e2")).alias("wins"), F.count("*").alias("queries"))


def zero_rate(results: DataFrame) -> DataFrame:
    """Share of predictions of nothing where there is something."""
    some = F.col("sigma_true") > 0
    return results.groupBy("estimator", "size").agg(F.count_if(some).alias("nonempty"), F.count_if(some & (F.col("sigma") == 0)).alias("zero_predictions"))


def bucket_curve(results: DataFrame) -> DataFrame:
    """Error curve over bucket counts (the size of a histogram estimator)."""
    return error_curve(results).orderBy("estimator", "size")


def simultaneous_failure(results: DataFrame, eps: float) -> DataFrame:
    """Share of samples (seeds) on which any query of the workload is off by more than eps."""
    worst = results.groupBy("estimator", "size", "seed").agg(F.max(abs_error()).alias("worst"))
    return worst.groupBy("estimator", "size").agg(F.count("*").alias("samples"), F.count_if(F.col("worst") > eps).alias("failed"), F.round(F.max("worst"), 9).alias("worst"))


def pivot_curve(curve: DataFrame, value: str = "mean_pct") -> DataFrame:
    estimators = [r[0] for r in curve.select("estimator").distinct().orderBy("estimator").collect()]  # a handful
    return curve.groupBy("size").pivot("estimator", estimators).agg(F.first(value)).orderBy("size")


def within_class(errors: DataFrame, eps: float) -> DataFrame:
    """Whether a sample is an eps-approximation of a class: the largest error over all ranges."""
    return errors.agg(F.max(abs_error()).alias("worst")).select("worst", (F.col("worst") <= eps).alias("is_approximation"))


# --- shattering, for small point sets on the driver


def projections(ranges: list[frozenset], points: frozenset) -> set[frozenset]:
    return {r & points for r in ranges}


def is_shattered(ranges: list[frozenset], points: frozenset) -> bool:
    return len(projections(ranges, points)) == 2 ** len(points)


def empirical_cap(ranges: list[frozenset], points: list) -> int:
    """Size of the largest shattered subset of a few points."""
    best = 0
    for k in range(1, len(points) + 1):
        if not any(is_shattered(ranges, frozenset(c)) for c in itertools.combinations(points, k)):
            break
        best = k
    return best
