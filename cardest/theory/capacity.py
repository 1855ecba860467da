"""Bounds on the capacity dimension (size of the largest shattered point set) of query classes, and sample sizes.

Bounds take base-2 logarithms, sample sizes natural ones. ``lemma`` variants are proved; ``table`` variants only reproduce
the published table of dimensions; ``direct`` and ``growth`` are numeric counting bounds, proved the same way and far
smaller.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable
from fractions import Fraction

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cardest.query.normalize import QueryClass

#: The constant of the eps-approximation theorem is known only from experiments.
C = 0.5


def cap_halfspaces(d: int) -> int:
    return d + 1


def growth(d: int, n: int) -> int:
    """Most subsets of ``n`` points that ranges of dimension ``d`` cut out."""
    return sum(math.comb(n, i) for i in range(min(d, n) + 1))


def cap_finite(k: int) -> int:
    """A family of ``k`` ranges shatters at most floor(log2 k) points."""
    return k.bit_length() - 1


def cap_boolean(d: int, h: int) -> float:
    """Unions and intersections of ``h`` ranges of dimension ``d >= 2``."""
    return 3 * d * h * math.log2(d * h)


def catalan(n: int) -> int:
    return math.comb(2 * n, n) // (n + 1)


def choices_of_members(n: int, d: int, h: int) -> int:
    """Ways to choose the ``h`` members among the subsets of ``n`` points, at most n^d each."""
    return n ** (d * h)


def boolean_shapes(h: int) -> int:
    """Formulas over ``h`` members: orders, connectives and bracketings; at most h^(2h)."""
    return math.factorial(h) * 2 ** (h - 1) * catalan(h - 1)


def cap_simple_select(m: int) -> int:
    return m + 1


def cap_select(m: int, b: int, variant: str = "lemma") -> float:
    """Selections of ``b`` clauses over ``m`` columns."""
    if variant == "table":
        return 2 * b if m == 1 else math.floor(2 * (m + 1) * b * math.log2((m + 1) * b))
    if b == 1:
        return cap_simple_select(m)
    if variant == "printed":
        return 2 * (m + 1) * b * math.log2((m + 1) * b)
    return cap_boolean(m + 1, b)


def cap_join(v1: float, v2: float, variant: str = "lemma") -> float:
    """One join of two tables whose selections have these dimensions, 2 at least."""
    if variant == "table":
        return v1 * v2
    v1, v2 = max(v1, 2), max(v2, 2)
    return 3 * (v1 + v2) * math.log2(v1 + v2)


def join_shapes(u: int, m: int, free_pair: bool = True) -> int:
    """Ways to join ``u`` tables: ``u - 1`` column pairs, six comparators each."""
    pairs = math.comb(math.comb(u * m, 2), u - 1) if free_pair else 1
    return pairs * 6 ** (u - 1)


def cap_multijoin(vs: Iterable[float], m: int = 1) -> float:
    """``u - 1`` joins of tables with these dimensions; needs m <= sum."""
    vs = [max(v, 2) for v in vs]
    total = sum(vs)
    if m > total:
        raise ValueError("more columns than the sum of the dimensions")
    return 4 * len(vs) * total * math.log2(len(vs) * total)


def cap_general(u: int, m: int, b: int) -> float:
    """Select-join queries of ``u`` tables, ``m`` columns, ``b`` Boolean operations."""
    x = (m + 1) * b * math.log2((m + 1) * b)
    return 12 * u * u * x * math.log2(3 * u * u * x)


def cap_numeric(m: int, b: int, u: int = 1, mode: str = "direct", free_pair: bool = False) -> int:
    """Largest set that counting does not exclude: the class cuts out at least 2^v subsets of v points.

    ``direct`` counts the one-clause ranges on n points (prefixes and suffixes per column), ``growth`` takes the growth
    function instead; both to the power of the clauses, times the formulas, to the power of the tables, times the joins.
    """

    def ranges(n: int) -> int:
        one = 2 * m * (n + 1) if mode == "direct" else growth(m + 1, n)
        return (one**b * 2 ** (b - 1) * catalan(b - 1)) ** u * (join_shapes(u, m, free_pair) if u > 1 else 1)

    v = 1
    while ranges(v + 1) >= 2 ** (v + 1) or ranges(2 * v + 16) >= 2 ** (2 * v + 16):
        v += 1
    return v


def sample_size(d: float, eps: float, delta: float, c: float = C, population: int | None = None) -> int:
    """Rows of an eps-approximation with probability 1 - delta; never more than the population."""
    n = math.ceil(c / eps**2 * (d + math.log(1 / delta)) - 1e-9)
    return n if population is None else min(n, population)


def relative_sample_size(d: float, p: float, eps: float, delta: float, c: float = C, population: int | None = None) -> int:
    """Rows of a relative (p, eps)-approximation."""
    n = math.ceil(c / (eps**2 * p) * (d * math.log(1 / p) + math.log(1 / delta)) - 1e-9)
    return n if population is None else min(n, population)


def eps_for_sample(s: int, d: float, delta: float, c: float = C) -> float:
    return math.sqrt(c * (d + math.log(1 / delta)) / s)


def delta_for_sample(s: int, d: float, eps: float, c: float = C) -> float:
    return min(1.0, math.exp(d - s * eps**2 / c))


def deterministic_size(d: float, eps: float) -> float:
    """Order of the size of a deterministic eps-approximation."""
    return d / eps**2 * math.log(d / eps)


def deterministic_time(d: float, eps: float, n: int) -> float:
    """Order of the time to build one."""
    return d ** (3 * d) * (1 / eps**2 * math.log(d / eps)) ** d * n


def sample_size_union(queries: int, eps: float, delta: float) -> int:
    """For a fixed list of queries by a union bound: grows with the list."""
    return math.ceil(math.log(2 * queries / delta) / (2 * eps**2))


def multidim_histogram_cells(k: int, m: int) -> int:
    return k**m


def sample_cells(s: int, m: int) -> int:
    """Values a sample stores, with its index column."""
    return s * (m + 1)


def join_synopses_count(columns: int) -> int:
    """Synopses needed to have every pair of columns."""
    return math.comb(columns, 2)


PROVED: dict[str, Callable[[QueryClass], float]] = {
    "lemma": lambda q: cap_select(q.m, q.b) if q.u == 1 else cap_join(cap_select(q.m, q.b), cap_select(q.m, q.b)) if q.u == 2 else cap_multijoin([cap_select(q.m, q.b)] * q.u, q.m),
    "general": lambda q: cap_general(q.u, q.m, q.b),
    "direct": lambda q: cap_numeric(q.m, q.b, q.u, "direct", free_pair=True),
    "growth": lambda q: cap_numeric(q.m, q.b, q.u, "growth", free_pair=True),
}


def best_bound(q: QueryClass) -> tuple[float, str]:
    """Smallest proved bound of the class, and which it is."""
    return min((f(q), name) for name, f in PROVED.items())


def bounds_table(spark: SparkSession, grid: Iterable[tuple[int, int, int, str]], eps: float = 0.05, delta: float = 0.05, c: float = C) -> DataFrame:
    """``u, m, b, variant, cap, eps, delta, sample_rows`` computed in SQL expressions over a grid of classes."""
    return bounds_frame(spark.createDataFrame(list(grid), "u int, m int, b int, variant string"), eps, delta, c)


def bounds_frame(rows: DataFrame, eps: float = 0.05, delta: float = 0.05, c: float = C) -> DataFrame:
    """The same for a table of classes ``u, m, b, variant``; its other columns are kept, at the end."""
    more = [n for n in rows.columns if n not in ("u", "m", "b", "variant")]
    x = (F.col("m") + 1) * F.col("b")
    v = F.when(F.col("b") == 1, (F.col("m") + 1).cast("double")).otherwise(3.0 * x * F.log2(x.cast("double")))
    xl = x * F.log2(x.cast("double"))
    u = F.col("u").cast("double")
    v2 = F.greatest(v, F.lit(2.0))
    table = F.when(F.col("m") == 1, 2.0 * F.col("b")).otherwise(F.floor(2.0 * x * F.log2(x.cast("double"))).cast("double"))
    cap = (
        F.when((F.col("variant") == "table") & (F.col("u") == 1), table)
        .when(F.col("variant") == "table", F.pow(table, F.lit(2.0)))
        .when(F.col("variant") == "general", 12.0 * u * u * xl * F.log2(3.0 * u * u * xl))
        .when(F.col("u") == 1, v)
        .when(F.col("u") == 2, 6.0 * v2 * F.log2(2.0 * v2))
        .otherwise(4.0 * u * u * v2 * F.log2(u * u * v2))
    )
    size = F.ceil(F.round(F.lit(c / eps**2) * (F.col("cap") + math.log(1 / delta)), 6)).cast("long")
    return rows.withColumn("cap", cap).select("u", "m", "b", "variant", F.round("cap", 6).alias("cap"), F.lit(eps).alias("eps"), F.lit(delta).alias("delta"), size.alias("sample_rows"), *more)


def growth_column(d: int, n: Column) -> Column:
    """``growth`` of a column of numbers of points, as an expression."""
    term = total = F.lit(1).cast("long")
    for i in range(1, d + 1):
        term = F.floor(term * (n - (i - 1)) / i).cast("long")
        total = total + term
    return total


def as_fraction(x: float) -> Fraction:
    return Fraction(x).limit_denominator(10**6)
