import datetime as dt

import pytest
from pyspark.sql import functions as F

from cardest.baselines import histogram as H
from cardest.catalog.common import SAMPLE_KEYS, bench
from cardest.estimators import exact, sample
from cardest.query import And, Clause, JoinEdge, Not, Or, Query, QueryClass
from cardest.query.frontend import Unsupported, from_sql
from cardest.sampling import build, store
from cardest.sources import register_views


@pytest.fixture(scope="module")
def db(spark, sf_dir):
    return bench(spark, sf_dir)


def pair(op, c1="c_acctbal", c2="s_acctbal"):
    return Query({"c": "customer", "s": "supplier"}, {"c": Clause("c_acctbal", "<=", 5000.0)}, (JoinEdge("c", c1, op, "s", c2),))


def test_sample_has_every_index_once_and_is_stable(db):
    one = build.create_sample(db, {"o": "orders"}, 500, 1, SAMPLE_KEYS).tables["o"]
    two = build.create_sample({"orders": db["orders"].repartition(7)}, {"o": "orders"}, 500, 1, SAMPLE_KEYS).tables["o"]
    rows = {(r["sampleindex"], r["o_orderkey"]) for r in one.collect()}
    assert sorted(i for i, _ in rows) == list(range(1, 501))
    assert rows == {(r["sampleindex"], r["o_orderkey"]) for r in two.collect()}


def test_prefix_of_larger_sample_is_smaller_sample(db):
    big = build.create_sample(db, {"o": "orders"}, 500, 1, SAMPLE_KEYS).prefix(100)
    small = build.create_sample(db, {"o": "orders"}, 100, 1, SAMPLE_KEYS)
    assert set(big.tables["o"].collect()) == set(small.tables["o"].collect())


def test_aliases_are_independent(db):
    sdb = build.create_sample(db, {"a": "nation", "b": "nation"}, 2000, 3, SAMPLE_KEYS)
    pairs = sample.paired_frame(sdb, ["a", "b"]).select("a__n_nationkey", "b__n_nationkey").distinct().count()
    assert pairs > 560  # nearly all of 625


def test_uniform_draws(db):
    n = {r["n_nationkey"]: r["count"] for r in build.create_sample(db, {"a": "nation"}, 5000, 3, SAMPLE_KEYS).tables["a"].groupBy("n_nationkey").count().collect()}
    assert sum((x - 200) ** 2 / 200 for x in n.values()) < 52  # chi-square, 24 degrees, 0.001


def test_file_and_partition_draws(spark, sf_dir, db):
    a = build.draw_by_file_row(spark, f"{sf_dir}/orders.parquet", 300, 5, "o", ["o_orderkey"])
    b = build.draw_by_partition(db["orders"].select("o_orderkey"), 300, 5, "o")
    for x in (a, b):
        assert sorted(r["sampleindex"] for r in x.collect()) == list(range(1, 301))
    # one file, rows in key order: the same draws as by key
    c = build.create_sample(db, {"o": "orders"}, 300, 5, SAMPLE_KEYS).tables["o"].select("o_orderkey", "sampleindex")
    assert set(a.select("o_orderkey", "sampleindex").collect()) == set(c.collect())


@pytest.mark.parametrize("op", ["<", "<=", ">", ">=", "=", "!="])
def test_paired_frame_equals_literal_definition_and_cross_counts(db, op):
    q = pair(op) if op not in ("=", "!=") else pair(op, "c_nationkey", "s_nationkey")
    sdb = build.create_sample(db, q.tables, 60, 2, SAMPLE_KEYS)
    fast = sample.estimate_all({"q": q}, sdb).first()["hits"]
    assert fast == sample.estimate_literal(q, sdb).first()["hits"]
    e = q.joins[0]
    left, right = sdb.tables["c"].where("c_acctbal <= 5000"), sdb.tables["s"]
    sql_op = "<>" if op == "!=" else op
    brute = left.crossJoin(right.withColumnRenamed("sampleindex", "i2")).where(f"{e.c1} {sql_op} {e.c2}").count()
    assert sample.cross_estimate(q, sdb).first()["pairs"] == brute


def test_exact_matches_join(db):
    q = Query({"c": "customer", "s": "supplier"}, {"c": Not(Clause("c_acctbal", "<=", 5000.0))}, (JoinEdge("c", "c_acctbal", "<", "s", "s_acctbal"),))
    c, s = db["customer"].where("c_acctbal > 5000"), db["supplier"]
    assert exact.exact_cardinality(q, db) == c.join(s, c.c_acctbal < s.s_acctbal).count()


def test_metamorphic(db):
    p, r = Clause("o_totalprice", "<=", 100000.0), Clause("o_orderstatus", "=", "F")
    sdb = build.create_sample(db, {"o": "orders"}, 400, 2, SAMPLE_KEYS)
    qs = {n: Query({"o": "orders"}, {"o": x}) for n, x in {"p": p, "not": Not(p), "r": r, "or": Or(p, r), "and": And(p, r)}.items()}
    got = {x["query_id"]: x["hits"] for x in sample.estimate_all(qs, sdb).collect()}
    assert got["p"] + got["not"] == 400
    assert got["or"] == got["p"] + got["r"] - got["and"]


def test_simultaneous_guarantee(db):
    from cardest.experiments import runs, workload as G

    qs = G.select_queries("orders_u", "t", {"u1": (0, 999)}, 1, 2, count=30)
    r = runs.seeds_results(db.db.spark, db, SAMPLE_KEYS, qs, 2400, range(4))
    assert r.where(F.abs(F.col("sigma") - F.col("sigma_true")) > 0.05).count() == 0


def test_small_table_is_its_own_sample_and_empty_tables_work(db):
    sdb = build.create_sample_for(db, {"s": "supplier"}, QueryClass(1, 1, 1), 0.05, 0.05, 1, SAMPLE_KEYS)
    q = {"q": Query({"s": "supplier"}, {"s": Clause("s_acctbal", ">", 0.0)})}
    assert sample.estimate_all(q, sdb).first()["sigma"] == pytest.approx(exact.exact_selectivity(q["q"], db))
    empty = build.create_sample({"supplier": db["supplier"].where("false")}, {"s": "supplier"}, 100, 1, SAMPLE_KEYS)
    assert sample.estimate_all(q, empty).first()["hits"] == 0


def test_guarantee_only_inside_the_class(db):
    sdb = build.create_sample_for(db, {"c": "customer", "s": "supplier"}, QueryClass(2, 1, 1), 0.1, 0.1, 1, SAMPLE_KEYS)
    assert sample.guarantee([pair("<")], sdb).kind == "absolute"
    assert sample.guarantee([pair("<")], sdb, "cross").kind == "none"
    wide = Query({"c": "customer", "s": "supplier"}, {"c": And(Clause("c_acctbal", "<=", 1.0), Clause("c_custkey", "<=", 5))}, pair("<").joins)
    assert sample.guarantee([wide], sdb).kind == "none"
    lo, hi = sample.relative_interval(0.5, 0.1, 0.2)
    assert lo < 0.5 < hi and sample.relative_interval(0.01, 0.1, 0.2) == (0.0, 0.1)


def test_store_round_trip(spark, db, tmp_path):
    sdb = build.create_sample_for(db, {"c": "customer", "s": "supplier"}, QueryClass(2, 1, 1), 0.2, 0.1, 1, SAMPLE_KEYS)
    store.save(sdb, str(tmp_path / "s"))
    back = store.load(spark, str(tmp_path / "s"))
    assert back.qclass == sdb.qclass and back.s == sdb.s
    assert set(back.tables["c"].collect()) == set(sdb.tables["c"].collect())
    assert store.needs_refresh({"q": 0.1}, {"q": 0.3}, 0.05) and not store.needs_refresh({"q": 0.1}, {"q": 0.15}, 0.05)


def test_front_end(spark, db):
    register_views(db.db, ("customer", "nation", "orders"))
    q = from_sql(spark, "select * from customer c, nation n where c.c_nationkey = n.n_nationkey and (c.c_acctbal > 10.5 or not c.c_custkey = 3) and n.n_name <> 'X'")
    assert q.tables == {"c": "customer", "n": "nation"} and q.joins == (JoinEdge("c", "c_nationkey", "=", "n", "n_nationkey"),)
    assert q.selections["c"] == Or(Clause("c_acctbal", ">", 10.5), Clause("c_custkey", "!=", 3))
    with pytest.raises(Unsupported, match="Window|Aggregate|Sort"):
        from_sql(spark, "select c_nationkey, count(*) from customer group by c_nationkey")


def test_independence_misleads_histograms_where_the_sample_does_not(spark):
    db = bench(spark, "/root/testdata/sf0.01")  # prices start to exceed 950 only there
    key = SAMPLE_KEYS["part"]
    pred = And(Clause("p_partkey", "<=", 299), Clause("p_retailprice", ">=", 950.0))
    q = Query({"p": "part"}, {"p": pred})
    truth = exact.exact_selectivity(q, db)
    stats = H.build(db["part"], ["p_partkey", "p_retailprice"], [key], H.HistogramConfig(100, 0))
    sdb = build.create_sample(db, {"p": "part"}, 1000, 1, SAMPLE_KEYS)
    assert abs(sample.estimate_all({"q": q}, sdb).first()["sigma"] - truth) < 0.05 < abs(H.combine(pred, stats) - truth)


def test_histogram_arithmetic():
    s = H.ColumnStats({5.0: 0.2}, [0.0, 10.0, 20.0], [4, 4], 9)
    assert H.sel_eq(s, 5) == 0.2 and H.sel_eq(s, 99) == 0
    assert H.sel_eq(s, 7) == pytest.approx(0.8 / 2 / 4)
    assert H.sel_le(s, 10) == pytest.approx(0.2 + 0.4) and H.sel_le(s, 15) == pytest.approx(0.2 + 0.6)
    assert H.sel_clause(s, "<", 5) == pytest.approx(H.sel_clause(s, "<=", 5) - 0.2)
    t = H.TableStats(1, {"a": s})
    p = Or(Clause("a", "<=", 15), Clause("a", ">=", 2))
    assert H.combine(p, t) == 1.0 and H.combine(p, t, "inclusion_exclusion") < 1.0
    assert H.combine(Not(Clause("a", "=", 5)), t) == pytest.approx(0.8)
    assert H.value_of(dt.datetime(1970, 1, 2)) == 86_400_000_000.0
    assert H.sel_join("=", s, s) + H.sel_join("!=", s, s) == pytest.approx(1)


def test_plans(db):
    from cardest import plans as P
    from cardest.catalog.plans import WIDE

    plans = P.enumerate_plans(WIDE)
    sdb = build.create_sample(db, WIDE.tables, 2000, 1, SAMPLE_KEYS)
    memo = P.SubplanMemo(sdb)
    cards = memo.cards(WIDE, P.all_sets(plans))
    memo.cards(WIDE, P.all_sets(plans))
    assert memo.asked == len(P.all_sets(plans))
    df, plan = P.optimize(WIDE, db, sdb)
    assert df.count() == exact.exact_cardinality(WIDE, db)
    assert P.plan_cost(plan, cards) == min(P.plan_cost(p, cards) for p in plans)
