"""Bounds are computed for classes read from the tables, and agree with SQL and with the functions they stand for."""

import duckdb
import pytest
from pyspark.sql import functions as F

from cardest.catalog import ORACLE, QUERIES
from cardest.query import QueryClass
from cardest.theory import capacity as K

NAMES = ["select_grid", "join_grid", "multijoin_grid", "general_grid", "relative_grid", "numeric_grid", "inverse", "union_contrast"]


@pytest.mark.parametrize("name", [f"bounds_{n}" for n in NAMES] + ["deterministic_construction", "growth_function_grid"])
def test_reads_a_table_and_equals_sql(spark, sf_dir, name):
    got = QUERIES[name](spark, sf_dir)
    assert any(f.endswith(("lineitem.parquet", "orders.parquet")) or "lineitem" in f or "orders" in f for f in got.inputFiles())
    con = duckdb.connect()
    for t in ("lineitem", "orders"):
        con.execute(f"create view {t} as select * from read_parquet('{sf_dir}/{t}.parquet')")
    cursor = con.execute(ORACLE[name])
    order = [c[0] for c in cursor.description]
    assert sorted(order) == sorted(got.columns)
    assert sorted(repr(tuple(r[c] for c in order)) for r in got.collect()) == sorted(map(repr, cursor.fetchall()))


def test_best_bound_of_every_class_of_the_table(spark, sf_dir):
    rows = QUERIES["bounds_best"](spark, sf_dir).collect()
    orders = duckdb.sql(f"select count(distinct l_orderkey) from '{sf_dir}/lineitem.parquet'").fetchall()[0][0]
    assert {r["u"] for r in rows} == {1, 2, 3} and sum(r["queries"] for r in rows) == 3 * orders
    for r in rows[:9]:
        assert (r["cap"], r["bound"]) == K.best_bound(QueryClass(r["u"], r["m"], r["b"]))


def test_growth_column(spark):
    rows = spark.range(0, 30).select("id", *[K.growth_column(d, F.col("id")).alias(f"d{d}") for d in (1, 2, 3)]).collect()
    assert all(r[f"d{d}"] == K.growth(d, r["id"]) for r in rows for d in (1, 2, 3))
