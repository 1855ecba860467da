"""The join experiments: every estimator predicts every query of the workload and its leaves."""

import pytest
from pyspark.sql import functions as F

from cardest.catalog import experiments as X
from cardest.catalog.common import SAMPLE_KEYS, bench
from cardest.experiments import runs as R
from cardest.sampling import build
from cardest.sampling.build import INDEX


def test_cross_sweep_equals_single_estimates(spark, sf_dir):
    from cardest.estimators import sample

    queries, sizes = X.JOIN[0], [50, 200]
    sdb = build.create_sample(bench(spark, sf_dir), next(iter(queries.values())).tables, 200, 42, SAMPLE_KEYS)
    got = {(r["query_id"], r["size"]): r["sigma"] for r in R.cross_sweep(queries, sdb, sizes).collect()}
    assert set(got) == {(n, s) for n in queries for s in sizes}
    for n in list(queries)[-3:]:
        for s in sizes:
            part = build.SampleDB({a: df.where(F.col(INDEX) <= s) for a, df in sdb.tables.items()}, sdb.sizes, s, sdb.seed)
            assert got[n, s] == pytest.approx(sample.cross_estimate(queries[n], part).first()["sigma"])


def test_join_figures_hold_all_queries_and_leaves(spark, sf_dir):
    queries = dict(list(X.JOIN[0].items())[:15])
    rows = R.join_results(spark, bench(spark, sf_dir), SAMPLE_KEYS, queries, [100], ["u1", "jc"], cross=True).collect()
    names = {*queries, *(f"{n}/{a}" for n in queries for a in "ab")}
    for estimator in ("index", "cross", "histogram"):
        assert sorted(r["query_id"] for r in rows if r["estimator"] == estimator) == sorted(names)
    leaf = {(r["estimator"], r["query_id"]): r["sigma"] for r in rows if "/" in r["query_id"]}
    assert all(leaf["index", n] == leaf["cross", n] for n in names if "/" in n)
