"""Selectivity of queries, and of every operator of their plans, from one sample.

Index-matched: of the s combinations whose rows share an index, the fraction that satisfies selections and join clauses.
The samples are joined on the index first, so the work is linear in s and the clauses are plain filters of wide rows.
Cross-sample: all combinations of sample rows, index ignored, counted from key counts without forming them; no guarantee.
"""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import dataclass
from functools import reduce
from operator import and_

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cardest.estimators.counting import counts_of
from cardest.estimators.exact import edge_count
from cardest.query.compile import edge_column, edge_expr, prefixed, to_column, to_expr
from cardest.query.ir import Query, clauses
from cardest.query.normalize import classify
from cardest.sampling.build import BROADCAST_DRAWS, INDEX, SampleDB
from cardest.theory import capacity


def paired_frame(sdb: SampleDB, aliases: Iterable[str]) -> DataFrame:
    """One row per index with the columns of all aliases, ``alias__column``: draws from the product of the tables."""
    frames = [prefixed(sdb.tables[a], a, keep=(INDEX,)) for a in aliases]
    small = sdb.s <= BROADCAST_DRAWS // 40
    return reduce(lambda x, y: x.join(F.broadcast(y) if small else y, INDEX), frames)


def condition(q: Query) -> str:
    """What a row of the paired frame must satisfy to count for the query, as SQL text."""
    parts = [to_expr(p, lambda c, a=a: f"`{a}__{c}`") for a, p in q.selections.items()] + [edge_expr(e) for e in q.joins]
    return " and ".join(parts) or "true"


def weight(q: Query) -> int:
    """Clauses of a query, as a measure of the code it compiles to."""
    return len(q.joins) + sum(1 for p in q.selections.values() for _ in clauses(p))


def frames(queries: dict[str, Query], sdb: SampleDB) -> list[tuple[tuple[str, ...], dict[str, Query]]]:
    """Queries by the aliases of the frame that counts them.

    Sets that share an alias share the frame of their union: every alias has one row per index, so a wider frame has the same
    indices. That does not hold without replacement, for whole tables and for empty ones, whose sets stay apart.
    """
    groups: list[tuple[frozenset[str], dict[str, Query]]] = []
    for name, q in queries.items():
        aliases = frozenset(q.aliases)
        full = sdb.replacement and not aliases & sdb.exact and all(sdb.sizes[a] for a in aliases)
        joined = [g for g in groups if (g[0] == aliases if not full else g[0] & aliases and not g[0] & sdb.exact and all(sdb.sizes[a] for a in g[0]))]
        merged: dict[str, Query] = {}
        for g in joined:
            aliases |= g[0]
            merged |= g[1]
            groups.remove(g)
        groups.append((aliases, merged | {name: q}))
    return [(tuple(sorted(aliases)), group) for aliases, group in groups]


def estimate_all(queries: dict[str, Query], sdb: SampleDB) -> DataFrame:
    """``query_id, s, hits, sigma, cardinality`` of every query; all nodes of a plan are counted in one pass of one frame."""
    whole = {n: math.prod(float(sdb.sizes[a]) for a in q.aliases) for n, q in queries.items()}
    parts = []
    for aliases, group in frames(queries, sdb):
        rows = sdb.sizes[aliases[0]] if set(aliases) <= sdb.exact else sdb.s
        hits = counts_of(paired_frame(sdb, aliases), {n: condition(q) for n, q in group.items()}, {n: weight(q) for n, q in group.items()}, keep=True)
        product = F.broadcast(hits.sparkSession.createDataFrame([(n, whole[n]) for n in group], "query_id string, __product double"))
        sigma = F.col("hits").cast("double") / F.lit(float(max(rows, 1)))
        parts.append(hits.join(product, "query_id").select("query_id", F.lit(rows).cast("long").alias("s"), "hits", sigma.alias("sigma"), (sigma * F.col("__product")).alias("cardinality")))
    return reduce(DataFrame.unionByName, parts)


def estimate_literal(q: Query, sdb: SampleDB) -> DataFrame:
    """The estimate as first defined: the query runs on the samples, then outputs with one common index are kept.

    Costs up to s to the power of the tables; a cross-check of the paired frame, which counts the same combinations.
    """
    out = None
    for a in q.aliases:
        df = sdb.tables[a]
        df = prefixed(df.where(to_column(q.selections[a])) if a in q.selections else df, a)
        out = df if out is None else out.crossJoin(df)
    first, *rest = q.aliases
    hits = out.where(reduce(and_, map(edge_column, q.joins), F.lit(True))).where(reduce(and_, [F.col(f"{a}__{INDEX}") == F.col(f"{first}__{INDEX}") for a in rest], F.lit(True)))
    return hits.agg(F.count("*").alias("hits")).select("hits", (F.col("hits").cast("double") / F.lit(float(sdb.s))).alias("sigma"))


def cross_of_samples(q: Query, sdb: SampleDB) -> DataFrame:
    """The naive product of samples, ``hits, sigma``: all combinations of sample rows taken for independent draws.

    The fraction is that of ``cross_estimate``, found by forming the combinations: s to the power of the tables, so for
    small samples only. Combinations share rows, hence no guarantee of the theorem holds for their number.
    """
    out = None
    for a in q.aliases:
        df = prefixed(sdb.tables[a].where(to_column(q.selections[a])) if a in q.selections else sdb.tables[a], a)
        out = df if out is None else out.crossJoin(df)
    hits = out.where(reduce(and_, map(edge_column, q.joins), F.lit(True))).agg(F.count("*").alias("hits"))
    return hits.select("hits", (F.col("hits").cast("double") / F.lit(float(sdb.s) ** len(q.aliases))).alias("sigma"))


def cross_estimate(q: Query, sdb: SampleDB) -> DataFrame:
    """Cross-sample estimate of a two-table query: ``pairs, sigma``; never materialises the pairs."""
    (e,) = q.joins
    left, right = (sdb.tables[a].where(to_column(q.selections[a])) if a in q.selections else sdb.tables[a] for a in (e.a1, e.a2))
    total = F.lit(float(sdb.s)) * F.lit(float(sdb.s))
    return edge_count(left, e.c1, e.op, right, e.c2).select(F.col("n").alias("pairs"), (F.col("n").cast("double") / total).alias("sigma"))


@dataclass(frozen=True)
class Guarantee:
    """What may be said of an estimate; ``kind`` is none where the query leaves the class or nothing is proved."""

    kind: str
    eps: float | None = None
    p: float | None = None


def guarantee(queries: Iterable[Query], sdb: SampleDB, method: str = "index") -> Guarantee:
    queries = list(queries)
    inside = sdb.qclass is not None and sdb.qclass.covers(classify(queries))
    joins = any(len(q.tables) > 1 for q in queries)
    if method == "cross" or not inside or (joins and not sdb.replacement):
        return Guarantee("none")
    return Guarantee("absolute", sdb.eps())


def relative_interval(sigma: float, p: float, eps: float) -> tuple[float, float]:
    """Where the true selectivity lies, given a relative (p, eps)-approximation and the estimate."""
    if sigma > (1 + eps) * p:
        return sigma / (1 + eps), min(1.0, sigma / (1 - eps))
    return 0.0, min(1.0, max(p, sigma / (1 - eps)))


def with_relative_interval(estimates: DataFrame, p: float, eps: float) -> DataFrame:
    """The same as columns ``lo`` and ``hi``."""
    sure = F.col("sigma") > (1 + eps) * p
    high = F.col("sigma") / (1 - eps)
    return estimates.withColumn("lo", F.when(sure, F.col("sigma") / (1 + eps)).otherwise(0.0)).withColumn("hi", F.least(F.lit(1.0), F.when(sure, high).otherwise(F.greatest(F.lit(p), high))))


def with_hoeffding(estimates: DataFrame, delta: float = 0.05) -> DataFrame:
    """An interval for each query on its own, without reference to a class."""
    half = F.sqrt(F.lit(math.log(2 / delta)) / (2 * F.col("s")))
    return estimates.withColumn("lo", F.greatest(F.lit(0.0), F.col("sigma") - half)).withColumn("hi", F.least(F.lit(1.0), F.col("sigma") + half))


def with_wilson(estimates: DataFrame, z: float = 1.96) -> DataFrame:
    s, x = F.col("s"), F.col("sigma")
    mid = (x + z * z / (2 * s)) / (1 + z * z / s)
    half = F.lit(z) * F.sqrt(x * (1 - x) / s + z * z / (4 * s * s)) / (1 + z * z / s)
    return estimates.withColumn("lo", F.greatest(F.lit(0.0), mid - half)).withColumn("hi", F.least(F.lit(1.0), mid + half))


def required_size(queries: Iterable[Query], eps: float, delta: float) -> int:
    return capacity.sample_size(capacity.best_bound(classify(queries))[0], eps, delta)
