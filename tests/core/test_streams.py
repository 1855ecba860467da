"""Arrivals come in time order, so that windows under a watermark do not depend on which part was written first."""

import duckdb
import pytest

from cardest.catalog import ORACLE, QUERIES


@pytest.mark.parametrize("name", ["stream_session", "stream_append_windows"])
def test_windows_follow_event_time(spark, sf_dir, name):
    d = sf_dir.replace("0.001", "0.01")
    con = duckdb.connect()
    con.execute(f"create view events as select * from '{d}/events.parquet'")
    want = con.execute(ORACLE[name])
    columns = [c[0] for c in want.description]
    want = sorted(map(repr, want.fetchall()))
    assert sorted(repr(tuple(r[c] for c in columns)) for r in QUERIES[name](spark, d).collect()) == want
