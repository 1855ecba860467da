"""Exact cardinalities: all selections of a table in one scan, joins from counts of keys wherever possible."""

from __future__ import annotations

import math
from collections import defaultdict
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from cardest.estimators.counting import batches, counts_of, hits_array
from cardest.query.compile import spark_value, to_column, to_dataframe, to_expr
from cardest.query.ir import MIRRORED, Query, clauses
from cardest.sources import stored


def key_counts(df: DataFrame, col: str) -> DataFrame:
    """``k, n``: partial counts per task first, so a hot key costs one row per task. NULL keys join nothing."""
    return df.where(F.col(f"`{col}`").isNotNull()).groupBy(F.col(f"`{col}`").alias("k")).agg(F.count("*").alias("n"))


def edge_count(left: DataFrame, c1: str, op: str, right: DataFrame, c2: str) -> DataFrame:
    """One row ``n``: pairs with ``left.c1 op right.c2``, from the two key-count tables; nothing larger is formed."""
    a, b = key_counts(left, c1), key_counts(right, c2)
    wide = "decimal(38,0)"
    product = F.col("n").cast(wide) * F.col("m").cast(wide)
    equal = a.join(b.withColumnRenamed("n", "m"), "k").agg(F.coalesce(F.sum(product), F.lit(0)).cast("long").alias("n"))
    if op == "=":
        return equal
    if op == "!=":
        totals = a.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("x")).crossJoin(b.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("y")))  # one row each
        return totals.crossJoin(equal).select((F.col("x").cast(wide) * F.col("y").cast(wide) - F.col("n")).cast("long").alias("n"))
    if op in (">", ">="):
        return edge_count(right, c2, MIRRORED[op], left, c1)
    # pairs with a < b: for every key of b the rows of a before it; <= takes the key's own rows too
    both = a.select("k", "n", F.lit(0).cast("long").alias("m")).unionByName(b.select("k", F.lit(0).cast("long").alias("n"), F.col("n").alias("m")))
    keys = both.groupBy("k").agg(F.sum("n").alias("n"), F.sum("m").alias("m"))
    upto = running_sum(keys, "k", "n")
    before = F.col("upto") if op == "<=" else F.col("upto") - F.col("n")
    return upto.agg(F.coalesce(F.sum(before.cast(wide) * F.col("m").cast(wide)), F.lit(0)).cast("long").alias("n"))


def equi_counts(queries: dict[str, Query], left: DataFrame, right: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """``*by, query_id, hits``: pairs of equi-joins on the same two columns, selections applied, within equal ``by``.

    Per batch of queries each side is one aggregation, whose counts of all queries stand in one array a key. Queries without
    pairs have no row.
    """
    (e,) = next(iter(queries.values())).joins
    wide, parts = "decimal(38,0)", []
    for batch in batches({n: "" for n in queries}, {n: 1 + sum(1 for p in q.selections.values() for _ in clauses(p)) for n, q in queries.items()}):
        sides = []
        for df, a, c, n in ((left, e.a1, e.c1, "n"), (right, e.a2, e.c2, "m")):
            conditions = {name: to_expr(queries[name].selections.get(a)) for name in batch}
            sides.append(df.where(F.col(f"`{c}`").isNotNull()).groupBy(*by, F.col(f"`{c}`").alias("k")).agg(hits_array(conditions, batch).alias(n)))
        cells = F.explode(F.arrays_zip(F.expr(f"array({', '.join(map(spark_value, batch))})").alias("query_id"), "n", "m")).alias("x")
        pairs = sides[0].join(sides[1], [*by, "k"]).select(*by, cells)
        parts.append(pairs.groupBy(*by, "x.query_id").agg(F.sum(F.col("x.n").cast(wide) * F.col("x.m").cast(wide)).cast("long").alias("hits")))
    return reduce(DataFrame.unionByName, parts)


def running_sum(df: DataFrame, key: str, value: str) -> DataFrame:
    """Adds ``upto``, the sum of ``value`` over keys up to and including the row's, without a single-task sort.

    Keys are parted by range; sums per part, one row each, give every part its start.
    """
    parts = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    ranged = stored(df.repartitionByRange(parts, key).withColumn("__part", F.spark_partition_id()), "running")
    totals = ranged.groupBy("__part").agg(F.sum(value).alias("__sum"))
    before = F.coalesce(F.sum("__sum").over(W.orderBy("__part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    starts = totals.select("__part", before.alias("__before"))
    own = F.sum(value).over(W.partitionBy("__part").orderBy(key).rowsBetween(W.unboundedPreceding, 0))
    return ranged.withColumn("upto", own).join(F.broadcast(starts), "__part").withColumn("upto", F.col("upto") + F.col("__before")).drop("__part", "__before")


def exact_all(queries: dict[str, Query], db: dict[str, DataFrame]) -> DataFrame:
    """``query_id, truth, sigma_true`` for every query.

    Selections of one table share its scan, equi-joins on the same columns share two; other two-table queries are counted
    from keys one by one; the rest run as joins.
    """
    single: dict[str, dict] = defaultdict(dict)
    equal: dict[tuple, dict[str, Query]] = defaultdict(dict)
    parts, sizes = [], {}
    for t in {t for q in queries.values() for t in q.tables.values()}:
        sizes[t] = db[t].count()
    for name, q in queries.items():
        if len(q.tables) == 1:
            ((a, t),) = q.tables.items()
            single[t][name] = to_expr(q.selections.get(a))
        elif len(q.tables) == 2 and len(q.joins) == 1:
            (e,) = q.joins
            if e.op == "=":
                equal[q.tables[e.a1], q.tables[e.a2], e][name] = q
                continue
            left, right = (db[q.tables[a]].where(to_column(q.selections.get(a))) for a in (e.a1, e.a2))
            parts.append(edge_count(left, e.c1, e.op, right, e.c2).select(F.lit(name).alias("query_id"), F.col("n").alias("hits")))
        else:
            parts.append(to_dataframe(q, db).agg(F.count("*").alias("hits")).select(F.lit(name).alias("query_id"), "hits"))
    for (t1, t2, _), group in equal.items():
        names = db[t1].sparkSession.createDataFrame([(n,) for n in group], "query_id string")
        found = equi_counts(group, db[t1], db[t2])
        parts.append(names.join(found, "query_id", "left").select("query_id", F.coalesce("hits", F.lit(0).cast("long")).alias("hits")))
    for t, conditions in single.items():
        parts.append(counts_of(db[t], conditions, {n: sum(1 for p in queries[n].selections.values() for _ in clauses(p)) for n in conditions}))
    whole = {n: math.prod(float(sizes[t]) for t in q.tables.values()) for n, q in queries.items()}
    spark = parts[0].sparkSession
    product = F.broadcast(spark.createDataFrame(list(whole.items()), "query_id string, __product double"))
    out = reduce(DataFrame.unionByName, parts).join(product, "query_id")
    return out.select("query_id", F.col("hits").alias("truth"), F.coalesce(F.try_divide(F.col("hits").cast("double"), F.col("__product")), F.lit(0.0)).alias("sigma_true"))


def exact_cardinality(q: Query, db: dict[str, DataFrame]) -> int:
    return exact_all({"q": q}, db).first()["truth"]


def exact_selectivity(q: Query, db: dict[str, DataFrame]) -> float:
    return exact_all({"q": q}, db).first()["sigma_true"]
