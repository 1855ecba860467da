"""Functions for SQL: sizing, histogram shares, draws as table functions."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cardest.query.normalize import QueryClass
from cardest.theory import capacity


def required_rows(u: int, m: int, b: int, eps: float, delta: float) -> int:
    """Sample rows for a class by the smallest proved bound."""
    return capacity.sample_size(capacity.best_bound(QueryClass(u, m, b))[0], eps, delta)


def register(spark: SparkSession) -> None:
    """``required_sample_size(u, m, b, eps, delta)`` for SQL text."""
    spark.udf.register("required_sample_size", required_rows, "long")


def hist_fraction(bounds: list[float]):
    """Share of an equi-depth histogram at or below a value, linear inside buckets; a vectorised function."""
    edges = [float(x) for x in bounds]

    @F.pandas_udf("double")
    def share(x: pd.Series) -> pd.Series:
        import numpy as np

        return pd.Series(np.interp(x.to_numpy(dtype=float), edges, np.linspace(0.0, 1.0, len(edges))))

    return share


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def equi_depth_udaf(x: pd.Series) -> list[float]:
    """Quartile bounds of a group, values at floor(j (n - 1) / 4): a grouped aggregate."""
    v = sorted(x.dropna())
    return [float(v[j * (len(v) - 1) // 4]) for j in range(5)] if v else []


def column_summary(group: pd.DataFrame) -> pd.DataFrame:
    """Grouped map: rows, distinct values and range of one column's values."""
    v = group["v"]
    return pd.DataFrame({"col": [group["col"].iloc[0]], "n": [len(v)], "ndv": [v.nunique()], "lo": [v.min()], "hi": [v.max()]})


def pair_counts(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
    """Cogrouped map: pairs of rows that share a key."""
    key = left["k"].iloc[0] if len(left) else right["k"].iloc[0]
    return pd.DataFrame({"k": [key], "pairs": [len(left) * len(right)]})


def threshold_bits(cuts: list[float]):
    """Per batch of values the subset of thresholds each satisfies, as bits: for empirical dimensions."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            bits = sum((b["v"] <= c).astype("int64") * (1 << i) for i, c in enumerate(cuts))
            yield pd.DataFrame({"v": b["v"], "bits": bits})

    return run


class _Draws:
    def eval(self, s: int, n: int, seed: int):
        import hashlib

        for i in range(1, s + 1):
            yield i, int(hashlib.md5(f"{seed}|t|{i}".encode()).hexdigest()[:15], 16) % n


class _Buckets:
    def eval(self, lo: float, hi: float, k: int):
        for j in range(k):
            yield j, lo + (hi - lo) * j / k, lo + (hi - lo) * (j + 1) / k


def table_functions(spark: SparkSession):
    """``sample_draws(s, n, seed)`` and ``even_buckets(lo, hi, k)`` as table functions for SQL."""
    draws = F.udtf(_Draws, returnType="sampleindex long, pos long")
    buckets = F.udtf(_Buckets, returnType="j int, lo double, hi double")
    spark.udtf.register("sample_draws", draws)
    spark.udtf.register("even_buckets", buckets)
    return draws, buckets


def log_size(d: float, eps: float, delta: float) -> float:
    return 0.5 / eps**2 * (d + math.log(1 / delta))
