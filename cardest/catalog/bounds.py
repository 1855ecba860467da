"""Capacity dimensions and sample sizes as tables.

The classes come from the data: an order stands for a query, its lines for clauses, their distinct line numbers for the columns
that the clauses are on.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cardest.query.normalize import QueryClass
from cardest.sources import load
from cardest.theory import capacity as K

MULTIJOIN_TABLES = (3, 4, 6)
GENERAL_TABLES = (1, 2, 3, 6)
EPS = DELTA = 0.05


def order_classes(spark, sf_dir) -> DataFrame:
    """``m, b, queries``: classes of the orders as queries, and how many orders are of each."""
    numbers = F.bit_count(F.bit_or(F.expr("shiftleft(1L, l_linenumber)")))  # line numbers are below 64
    orders = load(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(numbers.cast("int").alias("m"), F.count("*").cast("int").alias("b"))
    return orders.groupBy("m", "b").agg(F.count("*").alias("queries"))


def _each(df: DataFrame, name: str, values) -> DataFrame:
    return df.withColumn(name, F.explode(F.array(*[F.lit(v) for v in values])))


def _grid(spark, sf_dir, tables, *variants) -> DataFrame:
    return K.bounds_frame(_each(_each(order_classes(spark, sf_dir), "u", tables), "variant", variants), EPS, DELTA)


def bounds_select_grid(spark, sf_dir):
    return _grid(spark, sf_dir, (1,), "lemma", "table")


def bounds_join_grid(spark, sf_dir):
    """Joins of two tables with selections of an order's class on both."""
    return _grid(spark, sf_dir, (2,), "lemma", "table")


def bounds_multijoin_grid(spark, sf_dir):
    return _grid(spark, sf_dir, MULTIJOIN_TABLES, "lemma")


def bounds_general_grid(spark, sf_dir):
    return _grid(spark, sf_dir, GENERAL_TABLES, "general")


def bounds_relative_grid(spark, sf_dir):
    """Relative sizes: they grow as 1/p, and with the logarithm of 1/p."""
    base = _grid(spark, sf_dir, (1,), "lemma")
    p = F.explode(F.array(*[F.lit(x) for x in (0.5, 0.1, 0.01, 0.001)])).alias("p")
    rows = base.select("m", "b", "queries", "cap", p)
    size = F.ceil(F.round(0.5 / (EPS**2 * F.col("p")) * (F.col("cap") * F.log(1 / F.col("p")) + F.log(F.lit(1 / DELTA))), 4)).cast("long")
    return rows.withColumn("sample_rows", size)


def bounds_numeric_grid(spark, sf_dir):
    """Dimensions by counting, for selections and for joins of two tables; each class is counted once, by executors."""

    def counted(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for c in batches:
            rows = [(u, m, b, mode, K.cap_numeric(m, b, u, mode), n) for m, b, n in c.itertuples(index=False) for u, mode in ((1, "direct"), (1, "growth"), (2, "direct"))]
            yield pd.DataFrame([(*r[:5], K.sample_size(r[4], EPS, DELTA), r[5]) for r in rows], columns=["u", "m", "b", "mode", "cap", "sample_rows", "queries"])

    return order_classes(spark, sf_dir).mapInPandas(counted, "u int, m int, b int, mode string, cap int, sample_rows long, queries long")


def bounds_best(spark, sf_dir):
    """Smallest proved bound of each class over one, two and three tables, and which one it is."""

    def best(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for c in batches:
            rows = [(u, m, b, *K.best_bound(QueryClass(u, m, b)), n) for m, b, n in c.itertuples(index=False) for u in (1, 2, 3)]
            yield pd.DataFrame([(u, m, b, name, float(d), K.sample_size(d, EPS, DELTA), n) for u, m, b, d, name, n in rows], columns=["u", "m", "b", "bound", "cap", "sample_rows", "queries"])

    return order_classes(spark, sf_dir).mapInPandas(best, "u int, m int, b int, bound string, cap double, sample_rows long, queries long")


def bounds_inverse(spark, sf_dir):
    """Guarantee that the orders of a priority carry as a sample, per class: eps falls with the root of the size."""
    rows = _each(load(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.count("*").alias("s")), "d", (2, 31, 117))
    return rows.select("o_orderpriority", "s", "d", F.round(F.sqrt(0.5 * (F.col("d") + F.log(F.lit(20.0))) / F.col("s")), 9).alias("eps"))


def bounds_union_contrast(spark, sf_dir):
    """A union bound over a list grows with the list; the class bound does not. The lines of a quantity are one list."""
    rows = load(spark, sf_dir, "lineitem").groupBy("l_quantity").agg(F.count("*").alias("queries"))
    union = F.ceil(F.round(F.log(2.0 * F.col("queries") / DELTA) / (2 * EPS**2), 6)).cast("long")
    return rows.select("l_quantity", "queries", union.alias("union_rows"), F.lit(K.sample_size(K.cap_numeric(2, 2), EPS, DELTA)).cast("long").alias("class_rows"))


def storage_alternatives(spark, sf_dir):
    """Cells of a multi-dimensional histogram, of a sample, and synopses for all column pairs, by column count."""
    rows = spark.range(1, 9).select(F.col("id").alias("m"))
    return rows.select("m", F.pow(F.lit(10.0), F.col("m")).cast("long").alias("histogram_cells"), (F.lit(24000) * (F.col("m") + 1)).alias("sample_cells"), F.expr("cast(m * (m - 1) div 2 as bigint)").alias("synopses"))


def deterministic_construction(spark, sf_dir):
    """Order of the size of a deterministic approximation as fine as each discount of the lines."""
    rows = _each(load(spark, sf_dir, "lineitem").where("l_discount > 0").groupBy(F.col("l_discount").alias("eps")).agg(F.count("*").alias("rows")), "d", (2, 4))
    size = F.col("d") / (F.col("eps") * F.col("eps")) * F.log(F.col("d") / F.col("eps"))
    return rows.select("d", "eps", F.round(size, 6).alias("size"), "rows")


def growth_function_grid(spark, sf_dir):
    """Most subsets that ranges of dimension d cut out of an order's lines, by the number of lines."""
    lines = load(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count("*").cast("int").alias("n")).groupBy("n").agg(F.count("*").alias("orders"))
    subsets = F.when(F.col("d") == 1, K.growth_column(1, F.col("n"))).when(F.col("d") == 2, K.growth_column(2, F.col("n"))).otherwise(K.growth_column(3, F.col("n")))
    return _each(lines, "d", (1, 2, 3)).select("d", "n", subsets.alias("subsets"), "orders")


def shatter_intervals_small(spark, sf_dir):
    """Subsets of k points on a line that intervals cut out: all of two points, seven of eight of three."""
    ends = spark.range(0, 7).select(F.col("id").alias("x"))
    spans = ends.select(F.col("x").alias("lo"), F.explode(F.sequence(F.lit(0), F.lit(6))).alias("hi"))
    k = spans.withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(5))))
    bits = F.aggregate(F.sequence(F.lit(1), F.col("k")), F.lit(0), lambda acc, p: acc * 2 + F.when((p >= F.col("lo")) & (p <= F.col("hi")), 1).otherwise(0))
    return k.groupBy("k").agg(F.countDistinct(bits).alias("subsets")).select(F.col("k").cast("long").alias("k"), "subsets", (F.col("subsets") == F.pow(F.lit(2), F.col("k")).cast("long")).alias("shattered"))


def projection_counts_supplier(spark, sf_dir):
    """Distinct subsets of the suppliers cut out by balance thresholds: nested prefixes, the growth of dimension 1.

    A prefix is known by how many suppliers it holds.
    """
    from cardest.estimators.exact import key_counts, running_sum

    s = spark.read.parquet(f"{sf_dir}/supplier.parquet")
    sets = running_sum(key_counts(s, "s_acctbal"), "k", "n")
    return sets.agg((F.countDistinct("upto") + 1).alias("subsets"), F.coalesce(F.sum("n") + 1, F.lit(1)).alias("growth_bound"))


QUERIES = {f.__name__: f for f in (bounds_select_grid, bounds_join_grid, bounds_multijoin_grid, bounds_general_grid, bounds_relative_grid, bounds_numeric_grid, bounds_best, bounds_inverse, bounds_union_contrast, storage_alternatives, deterministic_construction, growth_function_grid, shatter_intervals_small, projection_counts_supplier)}


_CLASSES = "select m, b, count(*) as queries from (select count(distinct l_linenumber)::int as m, count(*)::int as b from lineitem group by l_orderkey) o group by 1, 2"


def _bounds_sql(tables, *variants) -> str:
    return f"""
with g as (select u, m, b, variant, queries from ({_CLASSES}) k, (select unnest({list(tables)})::int as u) t, (select unnest({list(variants)}) as variant) w),
v as (select *, ((m + 1) * b)::double as x, case when b = 1 then (m + 1)::double else 3 * ((m + 1) * b)::double * log2(((m + 1) * b)::double) end as v,
  case when m = 1 then 2.0::double * b else floor(2 * ((m + 1) * b)::double * log2(((m + 1) * b)::double)) end as t from g),
c as (select u, m, b, variant, queries, case when variant = 'table' and u = 1 then t when variant = 'table' then t * t
  when variant = 'general' then 12.0::double * u * u * x * log2(x) * log2(3.0::double * u * u * x * log2(x))
  when u = 1 then v when u = 2 then 6 * greatest(v, 2) * log2(2 * greatest(v, 2)) else 4.0::double * u * u * greatest(v, 2) * log2(u * u * greatest(v, 2)) end as cap from v)
select u, m, b, variant, round(cap, 6) as cap, 0.05::double as eps, 0.05::double as delta, ceil(round(200 * (cap + ln(20)), 6))::bigint as sample_rows, queries from c"""


def _numeric_sql() -> str:
    """Counting in logarithms; the slack lets equal counts stand as equal."""
    comb = "lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1)"
    catalan = "case when b = 1 then 0 else (lgamma(2 * b - 1) - lgamma(b) - lgamma(b + 1)) / ln(2) end"
    return f"""
with k as ({_CLASSES}),
n as (select n::double as n from range(1, 9000) r(n)),
ms as (select distinct m from k),
one as (select 'direct' as mode, m, n, log2(2 * m * (n + 1)) as bits from ms, n
  union all select 'growth', m, n, log2(sum(exp({comb}))) from ms, n, (select i::double as i from range(0, 65) r(i)) s where i <= m + 1 and i <= n group by m, n),
c as (select u, k.m, k.b, mode, n, queries, u * (b * bits + (b - 1) + {catalan}) + case when u = 2 then log2(6) else 0 end >= n - 1e-7 as open
  from k join one on k.m = one.m join (values (1, 'direct'), (1, 'growth'), (2, 'direct')) t(u, mode) using (mode)),
e as (select x.u, x.m, x.b, x.mode, x.queries, min(x.n - 1)::int as cap from c x join c y on x.u = y.u and x.m = y.m and x.b = y.b and x.mode = y.mode and y.n = 2 * x.n + 14
  where x.n >= 2 and not x.open and not y.open group by all)
select u, m, b, mode, cap, ceil(round(200 * (cap + ln(20)), 6))::bigint as sample_rows, queries from e"""


ORACLE = {
    "bounds_select_grid": _bounds_sql((1,), "lemma", "table"),
    "bounds_join_grid": _bounds_sql((2,), "lemma", "table"),
    "bounds_multijoin_grid": _bounds_sql(MULTIJOIN_TABLES, "lemma"),
    "bounds_general_grid": _bounds_sql(GENERAL_TABLES, "general"),
    "bounds_relative_grid": f"select m, b, queries, cap, p, ceil(round(0.5::double / (0.05::double * 0.05::double * p) * (cap * ln(1 / p) + ln(20)), 4))::bigint as sample_rows from ({_bounds_sql((1,), 'lemma')}) x, (select unnest([0.5, 0.1, 0.01, 0.001])::double as p) y",
    "bounds_numeric_grid": _numeric_sql(),
    "bounds_inverse": "select o_orderpriority, s, d, round(sqrt(0.5 * (d + ln(20)) / s), 9) as eps from (select o_orderpriority, count(*) as s from orders group by 1) a, (select unnest([2, 31, 117]) as d) b",
    "bounds_union_contrast": "select l_quantity, q as queries, ceil(round(ln(2.0::double * q / 0.05::double) / 0.005::double, 6))::bigint as union_rows, 3000::bigint as class_rows from (select l_quantity, count(*) as q from lineitem group by 1) a",
    "deterministic_construction": "select d::int as d, eps, round(d / (eps * eps) * ln(d / eps), 6) as size, n as rows from (select unnest([2, 4]) as d) a, (select l_discount as eps, count(*) as n from lineitem where l_discount > 0 group by 1) b",
    "storage_alternatives": "select m::bigint as m, pow(10, m)::bigint as histogram_cells, (24000 * (m + 1))::bigint as sample_cells, (m * (m - 1) // 2)::bigint as synopses from range(1, 9) r(m)",
    "growth_function_grid": "select d::int as d, n, (1 + n + case when d >= 2 then n * (n - 1) // 2 else 0 end + case when d >= 3 then n::bigint * (n - 1) * (n - 2) // 6 else 0 end)::bigint as subsets, orders from range(1, 4) a(d), (select n, count(*) as orders from (select count(*)::int as n from lineitem group by l_orderkey) x group by 1) y",
    "shatter_intervals_small": """
with s as (select k, lo, hi from range(1, 6) a(k), range(0, 7) b(lo), range(0, 7) c(hi)),
bits as (select k, lo, hi, sum(case when p between lo and hi then pow(2, p) else 0 end) as pattern from s, range(1, 6) d(p) where p <= k group by k, lo, hi)
select k::bigint as k, count(distinct pattern) as subsets, count(distinct pattern) = pow(2, k) as shattered from bits group by k""",
    "projection_counts_supplier": "with p as (select s_acctbal, sum(count(*)) over (order by s_acctbal) as upto from supplier where s_acctbal is not null group by 1) select count(distinct upto) + 1 as subsets, (select count(s_acctbal) + 1 from supplier) as growth_bound from p",
}
