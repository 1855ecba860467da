"""Relational operators around the methods: joins of every kind, windows, top-k, range and as-of joins."""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from cardest.sources import fresh_path, stored

#: Rows of a side that are broadcast at once: the driver holds them all while it builds their table.
BROADCAST_ROWS = 1_000_000
#: Of a range join: candidate pairs of a task, equal spans of a list, points of a list, lists of spans that a list of points meets.
PAIRS, BLOCK, BESIDE, SIDE_BLOCKS = 1 << 27, 252, 128, 16
HINTS = {"broadcast": "broadcast", "shuffle_hash": "shuffle_hash", "merge": "merge", "auto": None}


def join(left: DataFrame, right: DataFrame, on, how: str = "inner", strategy: str = "auto") -> DataFrame:
    """Equi-join with a physical strategy asked for by a hint on the right side; ``auto`` leaves it to the optimiser."""
    hint = HINTS[strategy]
    return left.join(right.hint(hint) if hint else right, on, how)


def broadcast_join(left: DataFrame, right: DataFrame, c1: str, c2: str, finish: Callable[[DataFrame], DataFrame], rows: int = BROADCAST_ROWS) -> DataFrame:
    """``finish`` of an inner equi-join whose right side is broadcast, at most about ``rows`` rows of it at a time.

    Beyond that both sides are written once, cut by the key, and the parts are joined one after another, so each left row
    meets one broadcast. A part that a hot key makes too large is cut again by row, and its left part meets every piece.
    With parts the result is a union of what ``finish`` makes of each: partial results, which the caller merges.
    """
    if left.schema[c1].dataType != right.schema[c2].dataType:
        raise ValueError("keys of different types hash differently")
    parts = math.ceil(right.count() / rows)
    if parts <= 1:
        return finish(join(left, right, left[c1] == right[c2], "inner", "broadcast"))
    spark, cut = left.sparkSession, []
    for df, c in ((left, c1), (right.withColumn("__row", F.monotonically_increasing_id()), c2)):
        path = fresh_path(spark, "broadcast-parts")
        df = df.where(F.col(c).isNotNull()).withColumn("__part", F.pmod(F.xxhash64(c), F.lit(parts)).cast("int"))
        df.write.partitionBy("__part").parquet(path)
        cut.append(spark.read.schema(df.schema).parquet(path))
    l, r = cut
    out = []
    for k, n in sorted(map(tuple, r.groupBy("__part").count().collect())):  # one row per part
        pieces = max(1, round(n / rows))
        for i in range(pieces):
            a, b = l.where(F.col("__part") == k).drop("__part"), r.where((F.col("__part") == k) & (F.pmod(F.xxhash64("__row"), F.lit(pieces)) == i)).drop("__part", "__row")
            out.append(stored(finish(join(a, b, a[c1] == b[c2], "inner", "broadcast")), "joined"))
    return reduce(DataFrame.unionByName, out) if out else finish(join(left, right, left[c1] == right[c2], "inner", "broadcast"))


def theta_join(left: DataFrame, right: DataFrame, condition: Column) -> DataFrame:
    """Nested loops: for results that are wanted themselves. Counts have a way without it (key counts, running sums)."""
    return left.join(right, condition)


def ne_join_count(left: DataFrame, right: DataFrame, c1: str, c2: str) -> DataFrame:
    from cardest.estimators.exact import edge_count

    return edge_count(left, c1, "!=", right, c2)


def less_join_sums(left: DataFrame, right: DataFrame, c1: str, c2: str, value: str, name: str) -> DataFrame:
    """One row: pairs ``n`` with ``left.c1 < right.c2`` and the sum over them of the right ``value``, both from running sums."""
    from cardest.estimators.exact import key_counts, running_sum

    wide = "decimal(38,0)"
    a = key_counts(left, c1).select("k", "n", F.lit(0).cast("long").alias("m"), F.lit(0).cast(wide).alias("v"))
    b = right.where(F.col(c2).isNotNull()).groupBy(F.col(c2).alias("k")).agg(F.count("*").alias("m"), F.coalesce(F.sum(F.col(value).cast("decimal(20,0)")), F.lit(0)).cast(wide).alias("v"))
    keys = a.unionByName(b.select("k", F.lit(0).cast("long").alias("n"), "m", "v")).groupBy("k").agg(*[F.sum(c).cast(wide).alias(c) for c in ("n", "m", "v")])
    before = (F.col("upto") - F.col("n")).cast("decimal(19,0)")
    total = lambda c: F.sum(before * F.col(c).cast("decimal(19,0)")).cast("long")
    out = running_sum(keys, "k", "n").agg(F.coalesce(total("m"), F.lit(0)).alias("n"), total("v").alias(name))
    return out.select("n", F.when(F.col("n") > 0, F.col(name)).alias(name))  # the sum of no pairs is null


def range_join(points: DataFrame, spans: DataFrame, point: str, lo: str, hi: str, width: float, pairs: int = PAIRS, block: int = BLOCK, beside: int = BESIDE) -> DataFrame:
    """Points inside intervals: both are cut into bins of ``width``, joined on the bin, checked within. No nested loop.

    Points of a bin travel in lists of about ``beside``, equal spans in lists of at most ``block``, and the pairs of two lists
    come out one after another, point by point: a page of a columnar file then repeats a short list of spans, which its
    encoding and compression store once. A bin is cut into cells of about ``pairs`` candidates and ``SIDE_BLOCKS`` full lists
    of spans at most; rows go to lists and cells by a hash of all their columns. The points of a list are checked before they
    leave it: Spark then hands on the pairs of one point at a time, where one generated loop over both lists kept them all.
    """
    rest = [c for c in spans.columns if c not in (lo, hi)] or [lo]
    p = points.select(F.struct(*points.columns).alias("__p"), F.floor(F.col(point) / F.lit(width)).alias("__bin"))
    s = spans.select(lo, hi, F.struct(*rest).alias("__s"), F.explode(F.sequence(F.floor(F.col(lo) / F.lit(width)), F.floor(F.col(hi) / F.lit(width)))).alias("__bin"))
    side = block * SIDE_BLOCKS
    lists, down, across = F.ceil(F.col("__n") / beside), F.ceil(F.col("__m") / side), F.ceil(F.col("__n") / pairs * F.least("__m", F.lit(side)))
    bins = p.groupBy("__bin").agg(F.count("*").alias("__n")).join(s.groupBy("__bin").agg(F.count("*").alias("__m")), "__bin")
    bins = stored(bins.select("__bin", "__n", "__m", lists.alias("__lists"), down.alias("__down"), across.alias("__across")), "range-bins")
    total = bins.agg(F.sum(F.col("__n").cast("double") * F.col("__m"))).first()[0] or 0.0
    piece = lambda c, n: F.pmod(F.xxhash64(c), F.col(n))
    every = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.col(n) - 1))
    cut = lambda n: F.explode(F.transform(F.sequence(F.lit(1), F.size("__all"), F.lit(n)), lambda at: F.slice("__all", at, n)))

    p = p.join(bins, "__bin").withColumn("__list", piece("__p", "__lists")).groupBy("__bin", "__list", "__down", "__across").agg(F.collect_list("__p").alias("__all"))
    p = p.withColumn("__points", cut(2 * beside)).select("__bin", F.pmod("__list", "__across").alias("__i"), every("__down").alias("__j"), "__points")
    s = s.join(bins, "__bin").withColumn("__j", piece("__s", "__down")).groupBy("__bin", "__j", "__across", lo, hi).agg(F.collect_list("__s").alias("__all"))
    s = s.withColumn("__spans", cut(block)).select("__bin", every("__across").alias("__i"), "__j", lo, hi, "__spans")
    if total > pairs:  # as many tasks as make about ``pairs`` candidates each; merged by their bytes, a few tasks would make all
        p, s = (x.repartition(math.ceil(total / pairs), "__bin", "__i", "__j") for x in (p, s))
    both = join(p, s, ["__bin", "__i", "__j"], strategy="merge")  # reads one list of points at a time, whichever side is small
    within = F.filter("__points", lambda x: (x[point] >= F.col(lo)) & (x[point] <= F.col(hi)))
    inside = both.select(F.explode(within).alias("__p"), lo, hi, "__spans")
    ends = [F.col(c) for c in (lo, hi) if c not in rest]
    if len(rest) == 1:
        inside = inside.select("__p", *ends, F.explode(F.col("__spans")[rest[0]]).alias(rest[0]))
    else:
        inside = inside.select("__p", *ends, F.explode("__spans").alias("__s")).select("__p", *ends, "__s.*")
    return inside.select("__p.*", *spans.columns)


def range_counts(points: DataFrame, spans: DataFrame, point: str, lo: str, hi: str, name: str) -> DataFrame:
    """Spans that hold a point, with the number ``name`` of points in them: from running sums over the values, no pair is formed.

    Points and ends of spans are one row per value; a span's count is that up to its end less that before its start.
    """
    from cardest.estimators.exact import key_counts, running_sum

    ends = spans.where(F.col(lo) <= F.col(hi)).select(F.explode(F.array(lo, hi)).alias("k")).distinct()
    keys = key_counts(points, point).unionByName(ends.withColumn("n", F.lit(0).cast("long"))).groupBy("k").agg(F.sum("n").alias("n"))
    upto = stored(running_sum(keys, "k", "n"), "upto")
    first = upto.select(F.col("k").alias(lo), (F.col("upto") - F.col("n")).alias("__before"))
    last = upto.select(F.col("k").alias(hi), F.col("upto").alias("__upto"))
    return spans.where(F.col(lo) <= F.col(hi)).join(first, lo).join(last, hi).withColumn(name, F.col("__upto") - F.col("__before")).drop("__before", "__upto").where(F.col(name) > 0)


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, value: str, tie: str) -> DataFrame:
    """Each left row with the last ``value`` of the right at or before it, per ``by``: one sort of the union, no join."""
    both = left.withColumn("__right", F.lit(0)).withColumn("__value", F.lit(None).cast(right.schema[value].dataType)).unionByName(
        right.select(*[c for c in (by, at, tie)], F.col(value).alias("__value")).withColumn("__right", F.lit(1)), allowMissingColumns=True
    )
    w = W.partitionBy(by).orderBy(F.col(at), F.desc("__right"), F.col(tie)).rowsBetween(W.unboundedPreceding, 0)
    return both.withColumn(f"last_{value}", F.last("__value", ignorenulls=True).over(w)).where("__right = 0").drop("__right", "__value")


def semi(left: DataFrame, right: DataFrame, on) -> DataFrame:
    return left.join(right, on, "left_semi")


def anti(left: DataFrame, right: DataFrame, on) -> DataFrame:
    return left.join(right, on, "left_anti")


def topk(df: DataFrame, by: str, k: int, ties: bool = False, tie: str | None = None) -> DataFrame:
    """The ``k`` largest: bounded heaps per task; with ties the rank of everything at the k-th value."""
    if not ties:
        return df.orderBy(F.desc(by), *([tie] if tie else [])).limit(k)
    edge = df.select(by).orderBy(F.desc(by)).limit(k).agg(F.min(by).alias("__edge"))
    return df.join(F.broadcast(edge), F.col(by) >= F.col("__edge")).drop("__edge")  # one row


def arg_extreme(df: DataFrame, by: list[str], what: str, at: str) -> DataFrame:
    return df.groupBy(*by).agg(F.min_by(what, at).alias(f"{what}_at_min"), F.max_by(what, at).alias(f"{what}_at_max"))


def equi_depth_ntile(df: DataFrame, col: str, buckets: int, tie: list[str]) -> DataFrame:
    """Bounds of equally full buckets by ``ntile``."""
    tile = F.ntile(buckets).over(W.orderBy(col, *tie))
    return df.select(col, tile.alias("bucket")).groupBy("bucket").agg(F.min(col).alias("lo"), F.max(col).alias("hi"), F.count("*").alias("n"))


def both(*conditions: Column) -> Column:
    return reduce(and_, conditions)
