"""The comparisons of estimators: violations, percent errors, wins, zero predictions, bucket counts, spread over seeds."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cardest.catalog.common import SAMPLE_KEYS, SEED, bench, derived_ctes, estimate_sql, sample_sql
from cardest.catalog.estimates import GRID, WORKLOADS, exact_counts_sql
from cardest.experiments import metrics as M
from cardest.experiments import runs as R
from cardest.experiments import workload as G
from cardest.sampling import build, store

EPS = 0.05
SIZES = [100, 300, 1000, 3800, 9600]
UNIFORM = WORKLOADS["est_select_orders_u_m2_b5"]
CORRELATED = WORKLOADS["est_select_orders_c_m2_b8"]
JOIN = WORKLOADS["est_join_uniform_m1_b1"]
JOIN5 = WORKLOADS["est_join_uniform_m1_b5"]
#: Classes of selections: columns a query may name, clauses, kind of columns.
CLASSES = {(m, b, kind): WORKLOADS[f"est_select_orders_{kind[0]}_m{m}_b{b}"] for kind, pairs in (("uniform", GRID), ("correlated", [(2, 2), (2, 5), (2, 8)])) for m, b in pairs}


def _uniform(spark, d, buckets=(100,)):
    return R.select_results(spark, bench(spark, d), SAMPLE_KEYS, UNIFORM[0], SIZES, list(G.UNIFORM), buckets)


def _correlated(spark, d, buckets=(100,), sizes=None):
    return R.select_results(spark, bench(spark, d), SAMPLE_KEYS, CORRELATED[0], sizes or [*SIZES, 17000], ["c1", "c2"], buckets, steps=True)


def fig_select_uniform(spark, d):
    """Percent error of sampling and histograms, independent columns."""
    return M.error_curve(_uniform(spark, d))


def fig_select_correlated(spark, d):
    """The same on correlated columns, where independence misleads the histograms."""
    return M.error_curve(_correlated(spark, d))


def fig_select_correlated_pivot(spark, d):
    return M.pivot_curve(M.error_curve(_correlated(spark, d)))


def fig_join(spark, d):
    """Index-matched, cross-sample and histograms on joins and the selections at their leaves."""
    return M.error_curve(R.join_results(spark, bench(spark, d), SAMPLE_KEYS, JOIN[0], SIZES, ["u1", "jc"], cross=True))


def fig_join_zero_rate(spark, d):
    """Small index-matched samples predict nothing where there is something; cross-sample does not."""
    return M.zero_rate(R.join_results(spark, bench(spark, d), SAMPLE_KEYS, JOIN[0], SIZES, ["u1", "jc"], buckets=(), cross=True))


def fig_bucket_insensitivity(spark, d):
    """More buckets do not mend independence."""
    return M.bucket_curve(_correlated(spark, d, buckets=(100, 1000, 10000), sizes=[1000])).where("estimator = 'histogram'")


def violations_select_uniform(spark, d):
    db = bench(spark, d)
    sdb = build.create_sample(db, {"t": "orders_u"}, UNIFORM[1], SEED, SAMPLE_KEYS)
    return M.violations(R.with_truth(R.sweep(UNIFORM[0], sdb, [UNIFORM[1]]), UNIFORM[0], db), EPS)


def err_select_uniform(spark, d):
    db = bench(spark, d)
    sdb = build.create_sample(db, {"t": "orders_u"}, UNIFORM[1], SEED, SAMPLE_KEYS)
    return M.error_curve(R.with_truth(R.sweep(UNIFORM[0], sdb, [UNIFORM[1]]), UNIFORM[0], db)).select("size", "mean_pct", "sd_pop_pct", "undefined", "queries")


def err_select_correlated(spark, d):
    db = bench(spark, d)
    sdb = build.create_sample(db, {"t": "orders_c"}, CORRELATED[1], SEED, SAMPLE_KEYS)
    return M.error_curve(R.with_truth(R.sweep(CORRELATED[0], sdb, [CORRELATED[1]]), CORRELATED[0], db)).select("size", "mean_pct", "sd_pop_pct", "undefined", "queries")


def measures_select_grid(spark, d):
    """Violations and percent errors for every class (m, b) of selections, each at its theorem's size.

    One sample and one exact pass for each kind of columns; the sample of a class is a prefix of the largest.
    """
    db, by, parts = bench(spark, d), ("columns", "m", "b", "size"), []
    for kind in ("uniform", "correlated"):
        classes = {f"m{m}_b{b}": (m, b, *work) for (m, b, k), work in CLASSES.items() if k == kind}
        queries = {f"{c}/{n}": q for c, (_, _, qs, _) in classes.items() for n, q in qs.items()}
        sdb = build.create_sample(db, next(iter(queries.values())).tables, max(s for *_, s in classes.values()), SEED, SAMPLE_KEYS).kept()
        wanted = spark.createDataFrame([(c, kind, m, b, s) for c, (m, b, _, s) in classes.items()], "class string, columns string, m int, b int, size long")
        swept = [R.sweep({f"{c}/{n}": q for n, q in qs.items()}, sdb, [s]) for c, (_, _, qs, s) in classes.items()]
        results = R.with_truth(reduce(DataFrame.unionByName, swept), queries, db).withColumn("class", F.substring_index("query_id", "/", 1))
        parts.append(results.join(F.broadcast(wanted), ["class", "size"]))  # one row a class
    results = reduce(DataFrame.unionByName, parts)
    return M.violations(results, EPS, by).join(M.error_curve(results, by).drop("queries"), list(by))


def violations_join(spark, d):
    """Violations of both estimators on joins with five clauses a side and the selections at their leaves."""
    return M.violations(R.join_results(spark, bench(spark, d), SAMPLE_KEYS, JOIN5[0], [1400, 7800, 19200], ["u1", "jc"]), EPS)


def violations_baseline_correlated(spark, d):
    return M.violations(_correlated(spark, d, sizes=[1000, 17000]), EPS)


def wins_select_uniform(spark, d):
    """Queries on which default histograms are closer than the sample."""
    return M.win_count(_uniform(spark, d).where("estimator = 'histogram' or estimator = 'index'"), "histogram", "index")


def q_error_select(spark, d):
    r = _uniform(spark, d)
    return r.withColumn("q", M.q_error()).groupBy("estimator", "size").agg(F.round(F.percentile("q", 0.5), 6).alias("median_q"), F.count_if(F.col("q").isNull()).alias("undefined"))


def failure_rate_seeds(spark, d):
    """Share of twenty samples of the theorem's size that are off by more than eps on any of a hundred queries."""
    q, s = WORKLOADS["est_select_orders_u_m1_b2"]
    return M.simultaneous_failure(R.seeds_results(spark, bench(spark, d), SAMPLE_KEYS, q, s, range(20)), EPS)


def ablation_bound_looseness(spark, d):
    """Below the theorem's size: samples start to fail only far below it."""
    q, _ = WORKLOADS["est_select_orders_u_m1_b2"]
    parts = [M.simultaneous_failure(R.seeds_results(spark, bench(spark, d), SAMPLE_KEYS, q, s, range(8)), EPS) for s in (100, 400, 1400)]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def sample_footprint(spark, d):
    sdb = build.create_sample(bench(spark, d), {"a": "orders_u", "b": "events_u"}, 2800, SEED, SAMPLE_KEYS)
    return store.footprint(sdb)


def eps_approximation_class(spark, d):
    """Whether a sample of the theorem's size is an eps-approximation of all prefixes of one column: every threshold tried."""
    from pyspark.sql import Window as W

    db = bench(spark, d)
    sdb = build.create_sample(db, {"t": "orders_u"}, 1200, SEED, SAMPLE_KEYS)
    n = sdb.sizes["t"]
    whole = db["orders_u"].groupBy("u1").agg(F.count("*").alias("n"))
    part = sdb.tables["t"].groupBy("u1").agg(F.count("*").alias("m"))
    w = W.orderBy("u1").rowsBetween(W.unboundedPreceding, 0)  # one row per value of the domain
    both = whole.join(part, "u1", "left").select((F.sum("n").over(w) / n).alias("sigma_true"), (F.sum(F.coalesce("m", F.lit(0))).over(w) / 1200).alias("sigma"))
    return M.within_class(both, EPS).select(F.round("worst", 9).alias("worst"), "is_approximation")


def workload_json(spark, d):
    """A generated workload as it is stored: one query per row."""
    return spark.createDataFrame([(n, q.to_json()) for n, q in UNIFORM[0].items()], "query_id string, ir string")


def workload_correlation(spark, d):
    """The derived pair is correlated as asked for, 3 to 4; the uniform columns are not."""
    db = bench(spark, d)
    c = db["orders_c"].agg(F.round(F.corr("c1", "c2"), 6).alias("normal_pair"))
    u = db["orders_u"].agg(F.round(F.corr("u1", "u2"), 6).alias("uniform_pair"))
    return c.crossJoin(u)  # one row each


def refresh_policy(spark, d):
    """Probe estimates of an old and a new sample: the same table asks for nothing, a changed one does."""
    db = bench(spark, d)
    q = UNIFORM[0]

    def probe(table, seed):
        from cardest.estimators import sample

        sdb = build.create_sample({"orders_u": table}, {"t": "orders_u"}, 2000, seed, SAMPLE_KEYS)
        return {r["query_id"]: r["sigma"] for r in sample.estimate_all(q, sdb).collect()}

    same = store.needs_refresh(probe(db["orders_u"], 1), probe(db["orders_u"], 2), EPS)
    moved = db["orders_u"].select("o_orderkey", *[(F.col(u) / 3).cast("long").alias(u) for u in G.UNIFORM], "jc")
    changed = store.needs_refresh(probe(db["orders_u"], 1), probe(moved, 2), EPS)
    return spark.createDataFrame([("same", same), ("changed", changed)], "table_state string, refresh boolean")


QUERIES = {
    f.__name__: f
    for f in (fig_select_uniform, fig_select_correlated, fig_select_correlated_pivot, fig_join, fig_join_zero_rate, fig_bucket_insensitivity, violations_select_uniform, err_select_uniform, err_select_correlated, measures_select_grid, violations_join, violations_baseline_correlated, wins_select_uniform, q_error_select, failure_rate_seeds, ablation_bound_looseness, sample_footprint, eps_approximation_class, workload_json, workload_correlation, refresh_policy)
}


def _errors(work) -> str:
    return f"select e.sigma, x.sigma_true, e.s as size, case when x.sigma_true > 0 then 100 * abs(e.sigma - x.sigma_true) / x.sigma_true when e.sigma = 0 then 0 end as p from ({estimate_sql(work[0], work[1])}) e join ({exact_counts_sql(work[0])}) x using (query_id)"


def _curve(work) -> str:
    return f"select size, round(avg(p), 6) as mean_pct, round(stddev_pop(p), 6) as sd_pop_pct, count(*) filter (where p is null) as undefined, count(*) as queries from ({_errors(work)}) z group by size"


def _classes(body) -> str:
    return " union all ".join(f"(select '{kind}' as columns, {m}::int as m, {b}::int as b, x.* from ({body(work)}) x)" for (m, b, kind), work in CLASSES.items())


def _measures(work) -> str:
    return f"select size, count(*) as queries, count(*) filter (where abs(sigma - sigma_true) > 0.05) as violations, round(avg(p), 6) as mean_pct, round(stddev_pop(p), 6) as sd_pop_pct, round(stddev_samp(p), 6) as sd_samp_pct, count(*) filter (where p is null) as undefined from ({_errors(work)}) z group by size"


ORACLE = {
    "measures_select_grid": _classes(_measures),
    "eps_approximation_class": f"""
with {', '.join([*derived_ctes(['orders_u']), *sample_sql('t', 'orders_u', 1200)])},
w as (select u1, count(*) as n from orders_u group by 1), p as (select u1, count(*) as m from s_t group by 1),
c as (select sum(n) over (order by w.u1)::double / sum(n) over () as whole, sum(coalesce(m, 0)) over (order by w.u1)::double / 1200 as part from w left join p on w.u1 = p.u1)
select round(max(abs(part - whole)), 9) as worst, max(abs(part - whole)) <= 0.05 as is_approximation from c""",
    "workload_correlation": f"with {', '.join(derived_ctes(['orders_c', 'orders_u']))} select (select round(corr(c1, c2), 6) from orders_c) as normal_pair, (select round(corr(u1, u2), 6) from orders_u) as uniform_pair",
    "violations_select_uniform": f"select 'index' as estimator, size, count(*) as queries, count(*) filter (where abs(sigma - sigma_true) > 0.05) as violations from ({_errors(UNIFORM)}) z group by size",
    "err_select_uniform": _curve(UNIFORM),
    "err_select_correlated": _curve(CORRELATED),
    "sample_footprint": "select 'a' as alias, 2800::bigint as sample_rows, (select count(*) from orders) as base_rows, 8 as columns, 22400::bigint as cells union all select 'b', 2800, (select count(*) from events), 8, 22400",
}
