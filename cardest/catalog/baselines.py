"""Histograms, multi-column statistics and the other baselines."""

from __future__ import annotations

from pyspark.sql import functions as F

from cardest.baselines import histogram as H
from cardest.baselines import others as B
from cardest.catalog.common import SAMPLE_KEYS, SEED, bench
from cardest.catalog.estimates import _native
from cardest.functions.rng import u60_sql
from cardest.query.ir import And, Clause, JoinEdge, Or, Query

ROWS, BUCKETS, ENTRIES = 4000, 50, 20


def _values(spark, d, table, cols, rows=ROWS):
    df = bench(spark, d)[table]
    key = SAMPLE_KEYS[table]
    return H.long_values(H.stats_sample(df, [key], rows, SEED), cols)


def stats_sample_orders(spark, d):
    """The rows statistics are built from: smallest hashes of the key."""
    return H.stats_sample(bench(spark, d)["orders"], ["o_orderkey"], ROWS, SEED).select("o_orderkey")


def mcv_orders(spark, d):
    m = H.mcv(_values(spark, d, "orders", ["o_custkey", "o_orderstatus"]), ENTRIES)
    return m.select("col", F.coalesce(F.col("v").cast("long").cast("string"), "text").alias("value"), "n")


def equidepth_orders(spark, d):
    v = _values(spark, d, "orders", ["o_totalprice", "o_custkey"])
    e = H.equi_depth(v, H.mcv(v, ENTRIES), BUCKETS)
    return e.select("col", "j", "lo", "hi", F.col("ndv").cast("long").alias("ndv"))


def equidepth_approximate(spark, d):
    """Bounds of the whole table in one pass, by a quantile sketch."""
    probs = [j / 10 for j in range(11)]
    return bench(spark, d)["lineitem"].agg(F.approx_percentile("l_extendedprice", probs, 10000).alias("bounds"))


def _stats(spark, d, table, cols, buckets=100, mcv=None, seed=SEED):
    key = SAMPLE_KEYS[table]
    return H.build(bench(spark, d)[table], cols, [key] if isinstance(key, str) else ["l_orderkey", "l_linenumber"], H.HistogramConfig(buckets, mcv), seed)


def _rows(spark, rows):
    return spark.createDataFrame([(n, round(float(x), 9)) for n, x in rows], "query_id string, sigma double")


def hist_leaf_lineitem(spark, d):
    """Leaf selectivities of every comparator and connective by baseline A, default statistics."""
    stats = _stats(spark, d, "lineitem", ["l_quantity", "l_discount", "l_extendedprice", "l_tax", "l_returnflag", "l_shipdate"])
    return _rows(spark, [(n, H.combine(q.selections["l"], stats)) for n, q in _native("lineitem").items()])


def hist_comparators(spark, d):
    stats = _stats(spark, d, "part", ["p_retailprice", "p_size"])
    return _rows(spark, [(f"{c} {op}", H.sel_clause(stats.columns[c], op, x)) for c, x in (("p_retailprice", 1200.0), ("p_size", 20)) for op in ("<", "<=", ">", ">=", "=", "!=")])


def hist_or_rules(spark, d):
    stats = _stats(spark, d, "part", ["p_retailprice", "p_size"])
    p = Or(Clause("p_size", "<=", 40), Clause("p_retailprice", ">=", 1000.0))
    return _rows(spark, [(r, H.combine(p, stats, r)) for r in ("add_capped", "inclusion_exclusion")])


def hist_join(spark, d):
    """Join factors of all six comparators between customer and supplier."""
    stats = {"c": _stats(spark, d, "customer", ["c_nationkey", "c_acctbal"]), "s": _stats(spark, d, "supplier", ["s_nationkey", "s_acctbal"])}
    edges = {op: JoinEdge("c", *(("c_nationkey", op, "s", "s_nationkey") if op in ("=", "!=") else ("c_acctbal", op, "s", "s_acctbal"))) for op in ("=", "!=", "<", "<=", ">", ">=")}
    return _rows(spark, [(op, H.edge_selectivity(e, stats)) for op, e in edges.items()])


def hist_plan_nodes(spark, d):
    from cardest.catalog.plans import WIDE

    cols = {"c": ["c_acctbal", "c_nationkey"], "s": ["s_acctbal", "s_nationkey"], "n": ["n_nationkey", "n_regionkey"], "r": ["r_regionkey"]}
    stats = {a: _stats(spark, d, t, cols[a]) for a, t in WIDE.tables.items()}
    order = list(WIDE.tables)
    nodes = {a: WIDE.restricted([a]) for a in order} | {"+".join(order[: i + 1]): WIDE.restricted(order[: i + 1]) for i in range(1, len(order))}
    return _rows(spark, [(n, H.selectivity(q, stats)) for n, q in nodes.items()])


def _buckets(k):
    def run(spark, d):
        stats = _stats(spark, d, "part", ["p_retailprice"], buckets=k)
        return _rows(spark, [(f"<= {x}", H.sel_le(stats.columns["p_retailprice"], float(x))) for x in range(900, 2100, 100)])

    return run


def multicol_density(spark, d):
    return B.multi_column_density(bench(spark, d)["lineitem"], [("l_returnflag", "l_linestatus"), ("l_quantity", "l_discount"), ("l_tax",)])


def multicol_density_approx(spark, d):
    return B.multi_column_density(bench(spark, d)["lineitem"], [("l_partkey", "l_suppkey"), ("l_orderkey",)], approximate=True)


def step_hist_quantity(spark, d):
    return B.step_histogram(bench(spark, d)["lineitem"], "l_quantity", 10)


def multicol_vs_single(spark, d):
    """Equalities on two columns, with and without their joint density."""
    part = bench(spark, d)["part"]
    dens = {frozenset(r["columns"].split(",")): r["ndv"] for r in B.multi_column_density(part, [("p_brand", "p_size")]).collect()}
    base = B.BaselineB(_stats(spark, d, "part", ["p_brand", "p_size"]), dens)
    first = part.orderBy("p_partkey").first()
    p = And(Clause("p_brand", "=", first["p_brand"]), Clause("p_size", "=", first["p_size"]))
    return _rows(spark, [("multi", base.selectivity(p)), ("single", base.single().selectivity(p))])


def grid_hist_part(spark, d):
    """Cells of a two-column grid; they see the correlation that independence misses."""
    part = bench(spark, d)["part"]
    g = B.grid_histogram(part, ["p_partkey", "p_retailprice"], 10)
    box = {"p_partkey": (float("-inf"), 299.0), "p_retailprice": (950.0, float("inf"))}
    stats = _stats(spark, d, "part", ["p_partkey", "p_retailprice"])
    pred = And(Clause("p_partkey", "<=", 299), Clause("p_retailprice", ">=", 950.0))
    truth = part.where("p_partkey <= 299 and p_retailprice >= 950").count() / part.count()
    return _rows(spark, [("grid", B.sel_grid(g, {k: (max(lo, -1e18), min(hi, 1e18)) for k, (lo, hi) in box.items()})), ("independence", H.combine(pred, stats)), ("truth", truth)])


def grid_hist_cells(spark, d):
    part = bench(spark, d)["part"]
    return B.grid_cells(part, ["p_size", "p_retailprice"], [[0.0, 10.0, 25.0, 50.0], [0.0, 1200.0, 1500.0, 3000.0]])


_SYN = Query({"o": "orders", "c": "customer"}, {"c": Clause("c_acctbal", ">=", 5000.0), "o": Clause("o_totalprice", "<=", 100000.0)}, (JoinEdge("o", "o_custkey", "=", "c", "c_custkey"),))


def join_synopsis_orders_customer(spark, d):
    """A sample of the join itself: right for this join only."""
    db = bench(spark, d)
    syn, rows = B.join_synopsis(_SYN, db, 1000, SEED, ["o__o_orderkey"])
    return B.sel_synopsis(syn, rows, _SYN, float(db["orders"].count()) * db["customer"].count()).select("hits", "s")


def spark_cbo_lineitem(spark, d):
    return B.spark_cbo(spark, f"{d}/lineitem.parquet", ["l_quantity", "l_discount"], "l_quantity <= 20 and l_discount >= 0.05", "cardest_cbo_lineitem")


QUERIES = {f.__name__: f for f in (stats_sample_orders, mcv_orders, equidepth_orders, equidepth_approximate, hist_leaf_lineitem, hist_comparators, hist_or_rules, hist_join, hist_plan_nodes, multicol_density, multicol_density_approx, step_hist_quantity, multicol_vs_single, grid_hist_part, grid_hist_cells, join_synopsis_orders_customer, spark_cbo_lineitem)} | {f"hist_buckets_{k}": _buckets(k) for k in (100, 1000, 10000)}

_SAMPLE = f"s as (select * from orders order by {u60_sql(SEED, repr('stats'), 'o_orderkey')}, o_orderkey limit {ROWS})"
_MCV = f"c as (select v, count(*) as n from s2 group by v), m as (select * from (select *, row_number() over (order by n desc, v) as rk from c) x where rk <= {ENTRIES})"


def _equi(col: str) -> str:
    return f"""(with {_SAMPLE}, s2 as (select {col}::double as v from s), {_MCV},
r as (select v, row_number() over (order by v) - 1 as k from s2 where v not in (select v from m)), z as (select count(*) as r from r),
b as (select j, v as hi from range(0, {BUCKETS + 1}) g(j), z, r where k = (j * (z.r - 1)) // {BUCKETS}),
l as (select j, lag(hi) over (order by j) as lo, hi from b)
select '{col}' as col, j::int as j, lo, hi, (select count(distinct v) from r where (v > lo and v <= hi) or (l.j = 1 and v = lo)) as ndv from l where j > 0)"""


def _mcv(col: str, text: str) -> str:
    return f"(with {_SAMPLE}, s2 as (select {col} as v from s), {_MCV} select '{col}' as col, {text} as value, n from m)"


def _part_sample(buckets: int) -> str:
    """The statistics sample of ``part`` for so many buckets, all rows if the table is smaller."""
    rows = f"(select ceil(4 * {buckets} * ln(2 * greatest(count(*), 2) / 0.01) / 0.25)::bigint from part)"
    return f"s as (select * from part order by {u60_sql(SEED, repr('stats'), 'p_partkey')}, p_partkey limit {rows})"


def _statistics(col: str, buckets: int, points) -> str:
    """Statistics of a column of ``s`` and, in ``{col}_at``, the shares at most, equal to and commonly equal to given points."""
    c, xs = col, ", ".join(f"({float(x)}::double)" for x in points)
    return f"""
{c}_n as (select {c}::double as v, count(*) as n from s where {c} is not null group by 1),
{c}_m as (select v, n / (select sum(n) from {c}_n)::double as f from {c}_n order by {c}_n.n desc, v limit {buckets}),
{c}_rest as (select greatest(0, 1 - sum(f)) as f from {c}_m),
{c}_r as (select {c}::double as v, row_number() over (order by {c}) - 1 as k from s where {c} is not null and {c}::double not in (select v from {c}_m)),
{c}_b as (select j, v from range(0, {buckets + 1}) g(j), {c}_r where k = (j * ((select count(*) from {c}_r) - 1)) // {buckets}),
{c}_d as (select hi.j, count(distinct r.v) as ndv from {c}_b hi join {c}_b lo on lo.j = hi.j - 1 join {c}_r r on (r.v > lo.v and r.v <= hi.v) or (hi.j = 1 and r.v = lo.v) group by 1),
{c}_x as (select x, (select max(j) from {c}_b where v <= x) as below, greatest(1, (select count(*) from {c}_b where v < x)) as bucket,
  coalesce((select sum(f) from {c}_m where v <= x), 0) as common, coalesce((select f from {c}_m where v = x), 0) as same from (values {xs}) p(x)),
{c}_at as (select x, same, common + (select f from {c}_rest) * case when below is null then 0 when below = {buckets} then 1
    else (below + coalesce((x - lo.v) / nullif(hi.v - lo.v, 0), 0)) / {buckets} end as le,
  case when same > 0 then same when below is null or x > (select max(v) from {c}_b) then 0
    else (select f from {c}_rest) / {buckets} / greatest(1, coalesce((select ndv from {c}_d where j = bucket), 0)) end as eq
  from {c}_x left join {c}_b lo on lo.j = below left join {c}_b hi on hi.j = below + 1)"""


def _comparators(col: str) -> str:
    shares = {"<": "greatest(0, le - same)", "<=": "le", ">": "1 - le", ">=": "1 - greatest(0, le - same)", "=": "eq", "!=": "1 - eq"}
    return " union all ".join(f"select '{col} {op}' as query_id, round({share}, 9) as sigma from {col}_at" for op, share in shares.items())


def _thresholds(k: int) -> str:
    return f"with {_part_sample(k)}, {_statistics('p_retailprice', k, range(900, 2100, 100))} select '<= ' || x::int as query_id, round(le, 9) as sigma from p_retailprice_at"


ORACLE = {
    "hist_comparators": f"with {_part_sample(100)}, {_statistics('p_retailprice', 100, [1200])}, {_statistics('p_size', 100, [20])} {_comparators('p_retailprice')} union all {_comparators('p_size')}",
    "hist_or_rules": f"""with {_part_sample(100)}, {_statistics('p_retailprice', 100, [1000])}, {_statistics('p_size', 100, [40])},
e as (select a.le as a, 1 - greatest(0, b.le - b.same) as b from p_size_at a, p_retailprice_at b)
select 'add_capped' as query_id, round(least(1, a + b), 9) as sigma from e union all select 'inclusion_exclusion', round(1 - (1 - a) * (1 - b), 9) from e""",
    "hist_buckets_100": _thresholds(100),
    "hist_buckets_1000": _thresholds(1000),
    "hist_buckets_10000": _thresholds(10000),
    "multicol_vs_single": f"""with {_part_sample(100)}, f as (select p_brand, p_size from part order by p_partkey limit 1)
select 'multi' as query_id, round(1 / (select count(*) from (select distinct p_brand, p_size from part))::double, 9) as sigma
union all select 'single', round((select avg((s.p_brand = f.p_brand)::int) * avg((s.p_size = f.p_size)::int) from s, f), 9)""",
    "stats_sample_orders": f"with {_SAMPLE} select o_orderkey from s",
    "mcv_orders": _mcv("o_custkey", "v::varchar") + " union all " + _mcv("o_orderstatus", "v"),
    "equidepth_orders": _equi("o_totalprice") + " union all " + _equi("o_custkey"),
    "multicol_density": "select 'l_returnflag,l_linestatus' as columns, (select count(*) from (select distinct l_returnflag, l_linestatus from lineitem)) as ndv union all select 'l_quantity,l_discount', (select count(*) from (select distinct l_quantity, l_discount from lineitem)) union all select 'l_tax', (select count(distinct l_tax) from lineitem)",
    "step_hist_quantity": "with c as (select l_quantity::double as v, count(*) as n from lineitem group by 1), u as (select *, sum(n) over (order by v) as upto, sum(n) over () as total from c), s as (select *, least(9, ((upto - 1) * 10) // total)::bigint as step from u) select step, min(v) as lo, max(v) as hi, sum(n)::bigint as rows, arg_max(n, v) as eq_rows, count(*) as ndv from s group by step",
    "grid_hist_cells": "select ((p_size > 10)::int + (p_size > 25)::int)::int as c0, ((p_retailprice > 1200)::int + (p_retailprice > 1500)::int)::int as c1, count(*) as n from part group by 1, 2",
    "join_synopsis_orders_customer": f"with j as (select o.*, c.c_acctbal from orders o join customer c on o_custkey = c_custkey order by {u60_sql(SEED, repr('synopsis'), 'o_orderkey')}, o_orderkey limit 1000) select count(*) filter (where c_acctbal >= 5000 and o_totalprice <= 100000) as hits, count(*) as s from j",
}
