"""Baseline A: most-common-value lists and equi-depth histograms per column, columns taken as independent.

Statistics of all columns of a table come from one sample of it and are built in a few passes over that sample; an
estimate is then arithmetic on the driver over at most some thousand buckets.
"""

from __future__ import annotations

import bisect
import datetime as dt
import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cardest.functions.rng import u60
from cardest.query.ir import MIRRORED, And, Clause, JoinEdge, Not, Or, Query
from cardest.query.normalize import to_nnf
from cardest.sources import stored


@dataclass(frozen=True)
class HistogramConfig:
    """Buckets, and entries of the most-common-value list (as many as buckets unless given)."""

    buckets: int = 100
    mcv: int | None = None
    rows: int | None = None
    gamma: float = 0.01

    @property
    def entries(self) -> int:
        return self.buckets if self.mcv is None else self.mcv


def stats_rows(population: int, buckets: int, gamma: float = 0.01, relative_error: float = 0.5) -> int:
    """Rows a statistics sample needs so that equi-depth buckets are within the relative error, but for chance gamma."""
    return math.ceil(4 * buckets * math.log(2 * max(population, 2) / gamma) / relative_error**2)


def stats_sample(df: DataFrame, key: list[str], rows: int, seed: int = 0) -> DataFrame:
    """The rows with the smallest hash of the key: one pass with bounded heaps, the same rows for all columns."""
    return df.withColumn("__h", u60(seed, "stats", *[F.col(k) for k in key])).orderBy("__h", *key).limit(rows).drop("__h")


def numeric(df: DataFrame, c: str):
    """A column as the number it is ordered by (epoch microseconds for times); None where order means nothing."""
    kind = df.schema[c].dataType
    if isinstance(kind, T.NumericType):
        return F.col(c).cast("double")
    if isinstance(kind, T.TimestampType | T.TimestampNTZType | T.DateType):
        return F.unix_micros(F.col(c).cast("timestamp")).cast("double")
    return None


def long_values(sample: DataFrame, cols: list[str]) -> DataFrame:
    """``col, v, text``: every value of every column as a row; numbers in ``v``, categories in ``text``."""
    parts = []
    for c in cols:
        v = numeric(sample, c)
        parts.append(F.struct(F.lit(c).alias("col"), (v if v is not None else F.lit(None).cast("double")).alias("v"), (F.lit(None).cast("string") if v is not None else F.col(c).cast("string")).alias("text")))
    return sample.select(F.explode(F.array(*parts)).alias("x")).select("x.*").where("v is not null or text is not null")


def mcv(values: DataFrame, entries: int) -> DataFrame:
    """``col, v, text, n``: per column the most frequent values, ties by smaller value."""
    counts = values.groupBy("col", "v", "text").agg(F.count("*").alias("n"))
    rank = F.row_number().over(W.partitionBy("col").orderBy(F.desc("n"), "v", "text"))
    return counts.withColumn("rank", rank).where(F.col("rank") <= entries).drop("rank")


def equi_depth(values: DataFrame, common: DataFrame, buckets: int) -> DataFrame:
    """``col, j, lo, hi, ndv``: per numeric column the bounds of equally full buckets of what is not most common.

    With values v_0 .. v_(r-1) in order, bound j is v at floor(j (r-1) / buckets); a bucket holds lo < v <= hi, the first lo too.
    """
    rest = values.where("v is not null").join(common.select("col", "v"), ["col", "v"], "left_anti")
    ranked = rest.withColumn("rank", F.row_number().over(W.partitionBy("col").orderBy("v")) - 1)
    sizes = rest.groupBy("col").agg(F.count("*").alias("r"))
    wanted = sizes.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(buckets)))).withColumn("rank", F.expr(f"(j * (r - 1)) div {buckets}").cast("int"))
    bounds = wanted.join(ranked, ["col", "rank"]).select("col", "j", F.col("v").alias("hi"))
    lo = F.lag("hi").over(W.partitionBy("col").orderBy("j"))
    spans = bounds.withColumn("lo", lo).where("j > 0")
    inside = ranked.select("col", "v").distinct()
    first = (F.col("j") == 1) & (F.col("v") == F.col("lo"))
    ndv = inside.join(spans, "col").where((F.col("v") > F.col("lo")) & (F.col("v") <= F.col("hi")) | first).groupBy("col", "j").agg(F.count("*").alias("ndv"))
    return spans.join(ndv, ["col", "j"], "left").select("col", "j", "lo", "hi", F.coalesce("ndv", F.lit(0)).alias("ndv"))


@dataclass
class ColumnStats:
    common: dict = field(default_factory=dict)  # value to frequency
    bounds: list[float] = field(default_factory=list)
    ndvs: list[int] = field(default_factory=list)
    ndv: float = 1.0
    categorical: bool = False

    @property
    def rest(self) -> float:
        return max(0.0, 1.0 - sum(self.common.values()))


@dataclass
class TableStats:
    """What the optimiser keeps of a table."""

    rows: int
    columns: dict[str, ColumnStats]


def build(df: DataFrame, cols: list[str], key: list[str], config: HistogramConfig, seed: int = 0) -> TableStats:
    n = df.count()
    rows = config.rows or stats_rows(n, config.buckets, config.gamma)
    sample = stats_sample(df, key, rows, seed) if rows < n else df
    values = stored(long_values(sample, cols), "stats")
    common = stored(mcv(values, config.entries), "stats-mcv")
    totals = {r["col"]: r for r in values.groupBy("col").agg(F.count("*").alias("n"), F.countDistinct("v", "text").alias("t"), F.countDistinct(F.coalesce(F.col("v").cast("string"), F.col("text"))).alias("ndv"), F.max(F.col("v").isNull()).alias("cat")).collect()}
    out = {c: ColumnStats(categorical=bool(totals[c]["cat"]), ndv=totals[c]["ndv"]) if c in totals else ColumnStats() for c in cols}
    for r in common.collect():  # at most ``entries`` rows per column
        out[r["col"]].common[r["text"] if r["v"] is None else r["v"]] = r["n"] / totals[r["col"]]["n"]
    for r in equi_depth(values, common, config.buckets).orderBy("col", "j").collect():  # at most ``buckets`` rows per column
        s = out[r["col"]]
        if not s.bounds:
            s.bounds.append(r["lo"])
        s.bounds.append(r["hi"])
        s.ndvs.append(r["ndv"])
    return TableStats(n, out)


def value_of(v):
    """A constant as statistics keep it."""
    if isinstance(v, dt.datetime):
        return float((v - dt.datetime(1970, 1, 1)) // dt.timedelta(microseconds=1))
    return float(v) if isinstance(v, int | float) and not isinstance(v, bool) else v


def sel_eq(s: ColumnStats, x) -> float:
    x = value_of(x)
    if x in s.common:
        return s.common[x]
    if s.categorical:
        return s.rest / max(1.0, s.ndv - len(s.common))
    if not s.bounds or not s.bounds[0] <= x <= s.bounds[-1]:
        return 0.0
    j = max(1, bisect.bisect_left(s.bounds, x))
    return s.rest / len(s.ndvs) / max(1, s.ndvs[j - 1])


def sel_le(s: ColumnStats, x) -> float:
    """``A <= x``: common values that satisfy it, full buckets, and a linear share of the bucket that holds x."""
    x = value_of(x)
    out = sum(f for v, f in s.common.items() if v <= x)
    if not s.bounds or s.categorical or x < s.bounds[0]:
        return out
    if x >= s.bounds[-1]:
        return out + s.rest
    j = bisect.bisect_right(s.bounds, x) - 1
    lo, hi = s.bounds[j], s.bounds[j + 1]
    return out + s.rest * (j + ((x - lo) / (hi - lo) if hi > lo else 0.0)) / len(s.ndvs)


def sel_clause(s: ColumnStats, op: str, x) -> float:
    if op == "=":
        return sel_eq(s, x)
    if op == "!=":
        return 1 - sel_eq(s, x)
    le = sel_le(s, x)
    # the histogram's share is the same for both; only a common value that equals x tells them apart
    lt = max(0.0, le - s.common.get(value_of(x), 0.0))
    return {"<=": le, "<": lt, ">": 1 - le, ">=": 1 - lt}[op]


def combine(p, stats: TableStats, or_rule: str = "add_capped") -> float:
    """A predicate under independence: AND multiplies; OR adds (capped at 1), or adds less the product."""
    if p is None:
        return 1.0
    if isinstance(p, Not):
        return combine(to_nnf(p), stats, or_rule)
    if isinstance(p, Clause):
        return sel_clause(stats.columns[p.col], p.op, p.value)
    parts = [combine(x, stats, or_rule) for x in p.parts]
    if isinstance(p, And):
        return math.prod(parts)
    return min(1.0, sum(parts)) if or_rule == "add_capped" else 1 - math.prod(1 - x for x in parts)


def sel_join(op: str, a: ColumnStats, b: ColumnStats) -> float:
    """Share of pairs with ``a op b``: common values matched one by one, the rest spread over distinct values or buckets."""
    if op == "!=":
        return 1 - sel_join("=", a, b)
    if op == "=":
        both = sum(f * b.common[v] for v, f in a.common.items() if v in b.common)
        only_a = sum(f for v, f in a.common.items() if v not in b.common)
        only_b = sum(f for v, f in b.common.items() if v not in a.common)
        left_a, left_b = max(1.0, a.ndv - len(a.common)), max(1.0, b.ndv - len(b.common))
        return min(1.0, both + only_a * b.rest / left_b + only_b * a.rest / left_a + a.rest * b.rest / max(left_a, left_b))
    if op in (">", ">="):
        return sel_join(MIRRORED[op], b, a)
    # integrate over the values of b: common ones, and the middle of every bucket
    total = sum(f * sel_clause(a, op, v) for v, f in b.common.items())
    for lo, hi in zip(b.bounds, b.bounds[1:], strict=False):
        total += b.rest / len(b.ndvs) * sel_clause(a, op, (lo + hi) / 2)
    return min(1.0, total)


def selectivity(q: Query, stats: dict[str, TableStats], or_rule: str = "add_capped") -> float:
    """Leaves times join factors; ``stats`` by alias."""
    out = math.prod(combine(p, stats[a], or_rule) for a, p in q.selections.items())
    for e in q.joins:
        out *= edge_selectivity(e, stats)
    return out


def edge_selectivity(e: JoinEdge, stats: dict[str, TableStats]) -> float:
    return sel_join(e.op, stats[e.a1].columns[e.c1], stats[e.a2].columns[e.c2])


__all__ = ["HistogramConfig", "Or", "TableStats", "build", "combine", "edge_selectivity", "equi_depth", "long_values", "mcv", "sel_clause", "sel_eq", "sel_join", "sel_le", "selectivity", "stats_rows", "stats_sample"]
