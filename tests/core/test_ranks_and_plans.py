"""Places by rank without a single-task sort, one frame for all nodes of a plan, and joins with few hits."""

import pytest
from pyspark.sql import functions as F

from cardest import plans as P
from cardest.catalog.common import SAMPLE_KEYS, bench
from cardest.catalog.plans import STAR, WIDE
from cardest.estimators import sample
from cardest.query.ir import JoinEdge, Query
from cardest.sampling import build

KEY_JOIN = Query({"o": "orders", "l": "lineitem"}, {}, (JoinEdge("o", "o_orderkey", "=", "l", "l_orderkey"),))


def test_ranks_are_places_in_order(spark):
    df = spark.range(1000).select(F.pmod(F.col("id") * 7, F.lit(10)).alias("a"), F.col("id").alias("b")).repartition(7)
    rows = build.ranked(df, ["a", "b"]).orderBy("pos").collect()
    assert [r["pos"] for r in rows] == list(range(1000))
    assert [(r["a"], r["b"]) for r in rows] == sorted((r["a"], r["b"]) for r in rows)


def test_ranks_with_one_hot_value_and_of_nothing(spark):
    df = spark.range(300).select(F.lit(1).alias("a"))
    assert sorted(r["pos"] for r in build.ranked(df, ["a"]).collect()) == list(range(300))
    assert build.ranked(df.where("false"), ["a"]).count() == 0
    assert build.draw_by_rank(df.where("false"), ["a"], 5, 1, "x").count() == 0


def test_a_ranked_sample_has_no_window(spark, sf_dir):
    drawn = build.create_sample(bench(spark, sf_dir), {"l": "lineitem"}, 50, 1, SAMPLE_KEYS, {"lineitem": ["l_quantity"]}).tables["l"]
    assert "Window" not in drawn._jdf.queryExecution().executedPlan().toString()
    assert drawn.count() == 50


def test_nodes_of_a_plan_share_one_frame(spark, sf_dir):
    sdb = build.create_sample(bench(spark, sf_dir), WIDE.tables, 300, 2, SAMPLE_KEYS)
    nodes = P.subqueries(WIDE, P.leaf_select_plan(WIDE, ["c", "n", "r", "s"]))
    assert len(sample.frames(nodes, sdb)) == 1
    got = {r["query_id"]: (r["hits"], r["cardinality"]) for r in sample.estimate_all(nodes, sdb).collect()}
    for name, q in nodes.items():
        alone = sample.estimate_all({name: q}, sdb).first()
        assert got[name] == (alone["hits"], pytest.approx(alone["cardinality"]))


def test_sets_without_a_common_index_stay_apart(spark, sf_dir):
    db = bench(spark, sf_dir)
    sets = {"c": WIDE.restricted(["c"]), "cn": WIDE.restricted(["c", "n"])}
    distinct = build.create_sample(db, {"c": "customer", "n": "nation"}, 30, 2, SAMPLE_KEYS, replacement=False)
    assert len(sample.frames(sets, distinct)) == 2
    assert sample.estimate_all(sets, distinct).where("query_id = 'c'").first()["hits"] == distinct.tables["c"].where("c_acctbal >= 8000").count()


def test_naive_product_is_the_cross_estimate(spark, sf_dir):
    sdb = build.create_sample(bench(spark, sf_dir), KEY_JOIN.tables, 200, 3, SAMPLE_KEYS)
    formed, counted = sample.cross_of_samples(KEY_JOIN, sdb).first(), sample.cross_estimate(KEY_JOIN, sdb).first()
    assert formed["hits"] == counted["pairs"] and formed["sigma"] == pytest.approx(counted["sigma"])


def test_joins_with_few_hits_are_taken_from_their_edges(spark, sf_dir):
    db = bench(spark, sf_dir)
    sdb = build.create_sample(db, STAR.tables, 2000, 4, SAMPLE_KEYS)
    pair = frozenset(["o", "l"])
    trusting, careful = P.SubplanMemo(sdb).cards(STAR, [pair]), P.SubplanMemo(sdb, P.FEW_HITS).cards(STAR, [pair])
    truth = P.true_cards(STAR, [pair], db)[pair]
    assert abs(careful[pair] - truth) < 0.5 * truth
    assert abs(careful[pair] - truth) <= abs(trusting[pair] - truth)


def test_partition_draws_read_the_wanted_columns_alone(spark, sf_dir):
    drawn = build.create_sample(bench(spark, sf_dir), {"l": "lineitem"}, 50, 1, SAMPLE_KEYS, {"lineitem": ["l_quantity"]}, method="partition").tables["l"]
    assert sorted(drawn.columns) == ["l_quantity", "sampleindex"]
    assert sorted(r["sampleindex"] for r in drawn.collect()) == list(range(1, 51))
    with pytest.raises(ValueError):
        build.create_sample({}, {}, 1, 1, {}, method="other")
