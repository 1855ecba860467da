"""Baseline B (step histograms, multi-column densities), grids, join synopses, Spark's cost-based estimate."""

from __future__ import annotations

import bisect
import math
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from cardest.baselines import histogram as H
from cardest.query.compile import prefixed, to_column
from cardest.query.ir import And, Clause, Query


# --- multi-column statistics


def step_histogram(df: DataFrame, col: str, steps: int = 200) -> DataFrame:
    """``step, lo, hi, rows, eq_rows, ndv``: at most ``steps`` steps with the exact frequency of every upper bound."""
    counts = df.where(F.col(col).isNotNull()).groupBy(F.col(col).cast("double").alias("v")).agg(F.count("*").alias("n"))
    total = counts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("total"))
    upto = F.sum("n").over(W.orderBy("v").rowsBetween(W.unboundedPreceding, 0))
    parts = counts.withColumn("upto", upto).join(F.broadcast(total)).withColumn("step", F.least(F.lit(steps - 1).cast("long"), F.expr(f"((upto - 1) * {steps}) div total")))
    return parts.groupBy("step").agg(F.min("v").alias("lo"), F.max("v").alias("hi"), F.sum("n").alias("rows"), F.max_by("n", "v").alias("eq_rows"), F.count("*").alias("ndv"))


def multi_column_density(df: DataFrame, colsets: list[tuple[str, ...]], approximate: bool = False) -> DataFrame:
    """``columns, ndv``: distinct combinations of every column set, all in one pass."""
    count = (lambda c: F.approx_count_distinct(F.struct(*c))) if approximate else (lambda c: F.countDistinct(F.struct(*c)))
    row = df.agg(*[count(list(c)).alias(f"d{i}") for i, c in enumerate(colsets)])
    return row.select(F.explode(F.array(*[F.struct(F.lit(",".join(c)).alias("columns"), F.col(f"d{i}").alias("ndv")) for i, c in enumerate(colsets)])).alias("x")).select("x.*")


@dataclass
class BaselineB:
    """Single-column histograms, and the density of column sets for conjunctions of equalities if ``multi``."""

    stats: H.TableStats
    densities: dict[frozenset[str], int] = field(default_factory=dict)
    multi: bool = True

    def selectivity(self, p) -> float:
        if self.multi and isinstance(p, And) and all(isinstance(x, Clause) and x.op == "=" for x in p.parts):
            ndv = self.densities.get(frozenset(x.col for x in p.parts))
            if ndv:
                return 1 / ndv
        return H.combine(p, self.stats, "inclusion_exclusion")

    def single(self) -> BaselineB:
        return replace(self, multi=False)


# --- multi-dimensional histograms


@dataclass
class Grid:
    """Rows per cell of a grid of quantile bins; only right for the columns it was built on, and k^m cells large."""

    columns: list[str]
    bounds: list[list[float]]
    cells: dict[tuple[int, ...], int]
    rows: int


def grid_cells(df: DataFrame, cols: list[str], bounds: list[list[float]]) -> DataFrame:
    """``c0, c1, ..., n``: bin of each column is the number of inner bounds below its value."""
    bins = []
    for i, (c, b) in enumerate(zip(cols, bounds, strict=True)):
        at = F.lit(0)
        for x in b[1:-1]:
            at = at + (F.col(c).cast("double") > F.lit(float(x))).cast("int")
        bins.append(at.alias(f"c{i}"))
    return df.groupBy(*bins).agg(F.count("*").alias("n"))


def grid_histogram(df: DataFrame, cols: list[str], k: int) -> Grid:
    cuts = df.agg(*[F.percentile(F.col(c).cast("double"), F.lit([j / k for j in range(k + 1)])).alias(f"q{i}") for i, c in enumerate(cols)]).first()
    bounds = [list(x or [0.0, 0.0]) for x in cuts]
    rows = grid_cells(df, cols, bounds).collect()  # at most k ** len(cols)
    cells = {tuple(r[:-1]): r[-1] for r in rows}
    return Grid(list(cols), bounds, cells, sum(cells.values()))


def sel_grid(g: Grid, ranges: dict[str, tuple[float, float]]) -> float:
    """Share of rows in a box, cells cut by it taken in proportion."""
    total = 0.0
    for cell, n in g.cells.items():
        share = 1.0
        for i, c in enumerate(g.columns):
            if c in ranges:
                lo, hi = ranges[c]
                a, b = g.bounds[i][cell[i]], g.bounds[i][cell[i] + 1]
                share *= (1.0 if lo <= a <= hi else 0.0) if b <= a else max(0.0, min(hi, b) - max(lo, a)) / (b - a)
        total += n * share
    return total / g.rows if g.rows else 0.0


def grid_bin(g: Grid, column: str, x: float) -> int:
    b = g.bounds[g.columns.index(column)]
    return max(0, min(len(b) - 2, bisect.bisect_left(b, x) - 1))


# --- join synopses


def join_synopsis(q: Query, db: dict[str, DataFrame], s: int, seed: int, key: list[str]) -> tuple[DataFrame, int]:
    """Sample of one pre-computed join (its ``s`` rows of smallest hash) and the join's size; selections come later."""
    from cardest.functions.rng import u60
    from cardest.query.compile import to_dataframe

    joined = to_dataframe(Query(q.tables, {}, q.joins), db)
    sample = joined.withColumn("__h", u60(seed, "synopsis", *[F.col(k) for k in key])).orderBy("__h", *key).limit(s).drop("__h")
    return sample, joined.count()


def sel_synopsis(sample: DataFrame, join_rows: int, q: Query, product: float) -> DataFrame:
    """``hits, s, sigma`` of the query's selections over the product of its tables."""
    from functools import reduce
    from operator import and_

    c = reduce(and_, [to_column(p, lambda c, a=a: f"{a}__{c}") for a, p in q.selections.items()], F.lit(True))
    row = sample.agg(F.count_if(c).alias("hits"), F.count("*").alias("s"))
    return row.select("hits", "s", (F.coalesce(F.try_divide(F.col("hits").cast("double"), F.col("s").cast("double")), F.lit(0.0)) * F.lit(join_rows / product)).alias("sigma"))


# --- the engine's own statistics


def spark_cbo(spark: SparkSession, path: str, cols: list[str], where: str, name: str) -> DataFrame:
    """``estimate, truth``: rows that Spark's cost-based optimiser expects of a filter, with column histograms.

    The table is registered over the given files and analysed once; session settings are put back.
    """
    conf = {"spark.sql.cbo.enabled": "true", "spark.sql.statistics.histogram.enabled": "true"}
    old = {k: spark.conf.get(k, None) for k in conf}
    for k, v in conf.items():
        spark.conf.set(k, v)
    try:
        spark.sql(f"DROP TABLE IF EXISTS {name}")
        spark.sql(f"CREATE TABLE {name} USING parquet LOCATION '{path}'")
        spark.sql(f"ANALYZE TABLE {name} COMPUTE STATISTICS FOR COLUMNS {', '.join(cols)}")
        df = spark.table(name).where(where)
        expected = df._jdf.queryExecution().optimizedPlan().stats().rowCount()
        guess = float(str(expected.get())) if expected.isDefined() else math.nan
    finally:
        for k, v in old.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    return df.agg(F.lit(guess).alias("estimate"), F.count("*").alias("truth"))


def wide(df: DataFrame, alias: str) -> DataFrame:
    return prefixed(df, alias)
