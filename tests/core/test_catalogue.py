"""A cross-section of the catalogue against DuckDB; the driver compares all of it."""

import duckdb
import pytest

from cardest import catalog

NAMES = ["est_select_lineitem", "est_join_le_customer_supplier", "est_cross_ne", "exact_join_gt", "mcv_orders", "equidepth_orders", "op_asof_join", "op_range_join", "stream_reservoir", "violations_select_uniform", "hist_comparators", "hist_or_rules", "hist_buckets_1000", "multicol_vs_single", "eps_approximation_class"]


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents"):
        con.execute(f"create view {t} as select * from read_parquet('{sf_dir}/{t}.parquet')")
    got = catalog.QUERIES[name](spark, sf_dir)
    cursor = con.execute(catalog.ORACLE[name])
    order = [d[0] for d in cursor.description]
    assert sorted(order) == sorted(got.columns)

    def clean(v):
        return round(v, 9) if isinstance(v, float) else v

    want = sorted(repr(tuple(map(clean, r))) for r in cursor.fetchall())
    assert sorted(repr(tuple(clean(r[c]) for c in order)) for r in got.collect()) == want


def test_every_oracle_has_a_query():
    assert set(catalog.ORACLE) <= set(catalog.QUERIES)


def test_estimates_never_shuffle_the_base_table(spark, sf_dir):
    from cardest.catalog.common import SAMPLE_KEYS, bench
    from cardest.sampling import build

    plan = build.create_sample(bench(spark, sf_dir), {"o": "orders"}, 100, 1, SAMPLE_KEYS).tables["o"]._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "CartesianProduct" not in plan and "hashpartitioning" not in plan
