"""Joins and streams whose sides are too large for the driver: in parts, through files, without pairs."""

import math
import re

import pytest
from pyspark.sql import functions as F

from cardest import operators as O
from cardest import streaming as S


@pytest.mark.parametrize("rows", [3, 7, 1000])
def test_broadcast_in_parts_equals_one_join(spark, rows):
    left = spark.createDataFrame([(k % 12, 1) for k in range(60)] + [(None, 1)], "k int, x long")
    right = spark.createDataFrame([(k, k) for k in range(10)] + [(3, 30)] * 9 + [(None, 5)], "j int, y long")  # a hot key, and nulls
    finish = lambda j: j.groupBy("y").agg(F.sum("x").alias("n"))
    got = O.broadcast_join(left, right, "k", "j", finish, rows).groupBy("y").agg(F.sum("n").alias("n"))
    want = left.join(right, F.col("k") == F.col("j")).groupBy("y").agg(F.sum("x").alias("n"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert O.broadcast_join(left.where("false"), right, "k", "j", finish, rows).count() == 0


def test_no_broadcast_is_larger_than_its_bound(spark, monkeypatch):
    sizes = []
    join = O.join
    monkeypatch.setattr(O, "join", lambda l, r, *a: (sizes.append(r.count()), join(l, r, *a))[1])
    right = spark.range(2000).select(F.col("id").alias("j"))
    O.broadcast_join(spark.range(50), right, "id", "j", lambda j: j.select("j"), 100)
    assert sum(sizes) == 2000 and max(sizes) <= 160


def test_appended_rows_go_to_files_not_to_the_driver(spark, sf_dir):
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    stream = S.read_events(spark, S.as_files(events), events.schema)
    out = S.drain(stream.select("event_id", "value"), "append", "appended_rows")
    assert out.inputFiles() and not spark.catalog.tableExists("appended_rows")
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, events.select("event_id", "value").collect()))


VALUES = [0.0, 1.0, 1.0, 1.25, 1.5, 1.5001, 2.0, 2.5, 7.0, 0.999, None, math.nan, math.inf]
SPANS = [(1, 1.0, 1.5), (2, 1.0, 1.5), (3, 2.0, 2.5), (4, 9.0, 9.5), (5, 2.0, 1.0), (6, None, 3.0), (7, 0.0, 7.0), (7, 7.0, 7.0)]


def _range_data(spark):
    inside = [(v, s) for v in VALUES for s, lo, hi in SPANS if v is not None and lo is not None and lo <= v <= hi]
    return spark.createDataFrame([(v,) for v in VALUES], "v double"), spark.createDataFrame(SPANS, "s int, lo double, hi double"), inside


def test_range_counts_equal_brute_force_and_form_no_pair(spark):
    points, spans, inside = _range_data(spark)
    got = O.range_counts(points, spans, "v", "lo", "hi", "n").groupBy("s").agg(F.sum("n").alias("n"))
    assert {r["s"]: r["n"] for r in got.collect()} == {s: sum(1 for _, x in inside if x == s) for _, s in inside}
    many = O.range_counts(spark.range(200_000).select(F.lit(1.0).alias("v")), spark.range(200_000).select("id", F.lit(1.0).alias("lo"), F.lit(1.5).alias("hi")), "v", "lo", "hi", "n")
    assert many.agg(F.sum("n")).first()[0] == 200_000**2  # pairs would take minutes


@pytest.mark.parametrize("pairs, block, beside", [(1 << 27, 252, 128), (40, 2, 3), (1, 1, 1)])
def test_range_join_equals_brute_force_however_it_is_cut(spark, pairs, block, beside):
    points = [(k, v) for k, v in enumerate(VALUES * 5)] + [(900, 1.25)] * 9 + [(None, 2.0)]
    spans = [(s, lo, hi, None if s == 2 else f"n{s}") for s, lo, hi in SPANS * 4] + [(None, 1.0, 1.5, "x"), (8, -0.5, 0.5, "y")]
    p, s = spark.createDataFrame(points, "k int, v double"), spark.createDataFrame(spans, "s int, lo double, hi double, name string")
    for columns in (["s", "lo", "hi", "name"], ["lo", "s", "hi"], ["lo", "hi"]):
        got = O.range_join(p, s.select(columns), "v", "lo", "hi", 1.0, pairs, block, beside)
        rows = [dict(zip(("s", "lo", "hi", "name"), x, strict=True)) for x in spans]
        want = [(k, v, *(x[c] for c in columns)) for k, v in points for x in rows if v is not None and x["lo"] is not None and x["lo"] <= v <= x["hi"]]
        assert got.columns == ["k", "v", *columns] and sorted(map(repr, map(tuple, got.collect()))) == sorted(map(repr, want))
    assert O.range_join(p.where("false"), s, "v", "lo", "hi", 1.0, pairs, block, beside).count() == 0


def test_pairs_of_a_range_join_are_small_on_disk(spark, tmp_path):
    points = spark.range(300).select("id", F.lit(1.25).alias("v"))
    spans = spark.range(20_000).select((F.col("id") * 7919 % 20_011).alias("s"), F.lit(1.0).alias("lo"), F.lit(1.5).alias("hi"))
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")  # as with large sides
    try:
        O.range_join(points, spans, "v", "lo", "hi", 1.0).select("id", "s").write.parquet(str(tmp_path / "out"))
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert spark.read.parquet(str(tmp_path / "out")).count() == 6_000_000
    assert sum(x.stat().st_size for x in (tmp_path / "out").glob("*.parquet")) < 6_000_000 * 0.3  # bytes a pair


def test_generated_code_loops_over_one_list_of_a_range_join(spark):
    points = spark.range(300).select("id", F.lit(1.25).alias("v"))
    spans = spark.range(500).select(F.col("id").alias("s"), F.lit(1.0).alias("lo"), F.lit(1.5).alias("hi"))
    for columns in (["s", "lo", "hi"], ["lo", "hi"]):
        out = O.range_join(points, spans.select(columns), "v", "lo", "hi", 1.0)
        assert len(out.collect()) == 150_000
        final = out._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0]
        stages = re.findall(r"(?:\*\s?\((\d+)\) )?Generate explode\(", final.split("SortMergeJoin")[0])
        assert len(stages) == 2 and len(set(stages)) == 2  # both in one stage keep the pairs of two lists in memory


def test_event_leaves_its_other_columns_before_the_state(spark, sf_dir, monkeypatch):
    seen, dedup = [], S.dedup
    monkeypatch.setattr(S, "dedup", lambda stream, keys: (seen.append(stream.columns), dedup(stream, keys))[1])
    from cardest.catalog import QUERIES

    n = QUERIES["stream_dedup"](spark, sf_dir).agg(F.sum("n")).first()[0]
    assert seen == [["at", "event_id", "event_type"]] and n == spark.read.parquet(f"{sf_dir}/events.parquet").count()
