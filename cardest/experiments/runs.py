"""Experiments: every estimator over a workload, as one table of results."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cardest.baselines import histogram as H
from cardest.baselines import others as B
from cardest.estimators import exact, sample
from cardest.estimators.counting import batches, hits_array, named_hits
from cardest.query.ir import Query
from cardest.sampling import build
from cardest.sampling.build import INDEX, SampleDB
from cardest.sources import stored

RESULTS = "query_id string, estimator string, size long, seed long, sigma double"


def sweep(queries: dict[str, Query], sdb: SampleDB, sizes: list[int], estimator: str = "index") -> DataFrame:
    """Index-matched estimates at many sample sizes from one build: prefixes of one paired frame, grouped by size."""
    aliases = next(iter(queries.values())).aliases
    frame = stored(sample.paired_frame(sdb, aliases), "sweep")
    wide = frame.withColumn("size", F.explode(F.array(*[F.lit(s).cast("long") for s in sizes]))).where(F.col(INDEX) <= F.col("size"))
    conditions = {n: sample.condition(q) for n, q in queries.items()}
    parts = []
    for batch in batches(conditions, {n: sample.weight(q) for n, q in queries.items()}):
        row = wide.groupBy("size").agg(hits_array(conditions, batch))
        cells = named_hits(batch)
        parts.append(row.select("size", cells).select("x.query_id", F.lit(estimator).alias("estimator"), "size", F.lit(sdb.seed).cast("long").alias("seed"), (F.col("x.hits").cast("double") / F.col("size")).alias("sigma")))
    return reduce(DataFrame.unionByName, parts)


def leaves(queries: dict[str, Query]) -> dict[str, Query]:
    """The selections at the leaves of join queries, as queries of one table each."""
    return {f"{n}/{a}": Query({a: t}, {a: q.selections[a]} if a in q.selections else {}) for n, q in queries.items() for a, t in q.tables.items()}


def cross_sweep(queries: dict[str, Query], sdb: SampleDB, sizes: list[int]) -> DataFrame:
    """Cross-sample estimates of equi-joins on the same columns at many sizes: key counts of both prefixes, multiplied."""
    (e,) = next(iter(queries.values())).joins
    size = F.explode(F.array(*[F.lit(s).cast("long") for s in sizes])).alias("size")
    left, right = (sdb.tables[a].select("*", size).where(F.col(INDEX) <= F.col("size")) for a in (e.a1, e.a2))
    names = left.sparkSession.createDataFrame([(n, s) for n in queries for s in sizes], "query_id string, size long")
    pairs = names.join(exact.equi_counts(queries, left, right, ("size",)), ["size", "query_id"], "left")
    sigma = F.coalesce("hits", F.lit(0)).cast("double") / (F.col("size") * F.col("size"))
    return pairs.select("query_id", F.lit("cross").alias("estimator"), "size", F.lit(sdb.seed).cast("long").alias("seed"), sigma.alias("sigma"))


def histogram_results(spark, queries: dict[str, Query], stats: dict[str, H.TableStats], size: int, estimator: str = "histogram", or_rule: str = "add_capped") -> DataFrame:
    rows = [(n, estimator, size, 0, float(H.selectivity(q, stats, or_rule))) for n, q in queries.items()]
    return spark.createDataFrame(rows, RESULTS)


def with_truth(results: DataFrame, queries: dict[str, Query], db) -> DataFrame:
    truth = stored(exact.exact_all(queries, db), "truth").select("query_id", "sigma_true")
    return stored(results.join(truth, "query_id"), "results")


def steps_results(spark, queries: dict[str, Query], df: DataFrame, columns: list[str], key: str, steps: int = 200) -> DataFrame:
    """Baseline B over selections of one table, with single-column statistics and with the columns' joint density too."""
    (alias,) = next(iter(queries.values())).tables
    density = B.multi_column_density(df, [tuple(columns)]).first()  # one row
    base = B.BaselineB(H.build(df, columns, [key], H.HistogramConfig(steps)), {frozenset(columns): density["ndv"]})
    kinds = {"steps_multi": base, "steps_single": base.single()}
    rows = [(n, kind, steps, 0, float(b.selectivity(q.selections[alias]))) for kind, b in kinds.items() for n, q in queries.items()]
    return spark.createDataFrame(rows, RESULTS)


def select_results(spark, db, keys, queries: dict[str, Query], sizes: list[int], columns: list[str], buckets=(100,), seed: int = 42, steps: bool = False) -> DataFrame:
    """Sampling at several sizes, baseline A at several bucket counts and, if asked for, baseline B, over selections of one table."""
    ((a, t),) = next(iter(queries.values())).tables.items()
    sdb = build.create_sample(db, {a: t}, max(sizes), seed, keys)
    parts = [sweep(queries, sdb, sizes)]
    for k in buckets:
        parts.append(histogram_results(spark, queries, {a: H.build(db[t], columns, [keys[t]], H.HistogramConfig(k))}, k))
    if steps:
        parts.append(steps_results(spark, queries, db[t], columns, keys[t]))
    return with_truth(reduce(DataFrame.unionByName, parts), queries, db)


def join_results(spark, db, keys, queries: dict[str, Query], sizes: list[int], columns: list[str], buckets=(100,), seed: int = 42, cross: bool = False) -> DataFrame:
    """The same for joins and the selections at their leaves, on request with the cross-sample estimator over all of them.

    On a leaf both sample estimators are the same fraction of one sample.
    """
    tables = next(iter(queries.values())).tables
    sdb = build.create_sample(db, tables, max(sizes), seed, keys)
    single = leaves(queries)
    both = {**queries, **single}
    parts = [sweep(both, sdb, sizes)]
    if cross:
        small = SampleDB({a: stored(df, "cross") for a, df in sdb.tables.items()}, sdb.sizes, sdb.s, sdb.seed)
        parts.append(cross_sweep(queries, small, sizes))
        parts.append(parts[0].where(F.col("query_id").isin(list(single))).withColumn("estimator", F.lit("cross")))
    for k in buckets:
        parts.append(histogram_results(spark, both, {a: H.build(db[t], columns, [keys[t]], H.HistogramConfig(k)) for a, t in tables.items()}, k))
    return with_truth(reduce(DataFrame.unionByName, parts), both, db)


def seeds_results(spark, db, keys, queries: dict[str, Query], size: int, seeds: range) -> DataFrame:
    """One sample per seed, all queries on each."""
    tables = next(iter(queries.values())).tables
    population = {t: db[t].count() for t in tables.values()}
    parts = [sweep(queries, build.create_sample(db, tables, size, s, keys, sizes=population), [size]) for s in seeds]
    return with_truth(reduce(DataFrame.unionByName, parts), queries, db)
