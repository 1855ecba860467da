"""Queries over whole tables against DuckDB, and against brute force on a table with nulls and ties."""

import duckdb
import pytest

from cardest import catalog
from cardest import operators as O

NAMES = ["op_join_left", "op_join_right", "op_join_full", "op_join_theta", "op_range_join", "op_range_join_counts", "projection_counts_supplier"]


@pytest.mark.parametrize("name", NAMES)
def test_whole_table_query_equals_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in ("customer", "supplier", "part", "events", "documents", "labels"):
        con.execute(f"create view {t} as select * from read_parquet('{sf_dir}/{t}.parquet')")
    assert " % " not in catalog.ORACLE[name] and "key <" not in catalog.ORACLE[name] and "id <" not in catalog.ORACLE[name]
    got = catalog.QUERIES[name](spark, sf_dir)
    cursor = con.execute(catalog.ORACLE[name])
    order = [d[0] for d in cursor.description]
    assert sorted(order) == sorted(got.columns)
    assert sorted(repr(tuple(r[c] for c in order)) for r in got.collect()) == sorted(map(repr, cursor.fetchall()))


def test_less_join_sums(spark):
    left = [(1.0,), (1.0,), (2.0,), (None,), (5.0,)]
    right = [(1.0, 7), (2.0, 8), (2.0, None), (3.0, -2), (None, 9)]
    l, r = spark.createDataFrame(left, "x double"), spark.createDataFrame(right, "y double, v long")
    pairs = [v for (x,) in left for y, v in right if x is not None and y is not None and x < y]
    assert tuple(O.less_join_sums(l, r, "x", "y", "v", "k").first()) == (len(pairs), sum(v for v in pairs if v is not None))
    assert tuple(O.less_join_sums(l, r.where("false"), "x", "y", "v", "k").first()) == (0, None)
