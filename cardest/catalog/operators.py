"""Operators around the methods, one small query each, with SQL."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from cardest import operators as O
from cardest.functions import udfs
from cardest.functions.rng import u60, u60_sql
from cardest.query.compile import to_dataframe
from cardest.query.frontend import from_sql
from cardest.sources import fresh_path, load, load_db, numeric_views, read_any, register_views, with_row_position

QUERIES: dict = {}
ORACLE: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE[f.__name__] = sql
        return f

    return add


def t(spark, d, name):
    return load(spark, d, name)


# --- scans, sources, sinks


@query("select l_orderkey, l_quantity from lineitem where l_shipdate >= timestamp '1997-01-01' and l_quantity <= 5")
def op_scan_pushed(spark, d):
    return t(spark, d, "lineitem").select("l_orderkey", "l_quantity", "l_shipdate").where("l_shipdate >= timestamp_ntz '1997-01-01 00:00:00' and l_quantity <= 5").drop("l_shipdate")


@query("select count(*) as rows, count(*)::bigint as positions from lineitem")
def op_scan_positions(spark, d):
    rows = with_row_position(spark, f"{d}/lineitem.parquet")
    return rows.agg(F.count("*").alias("rows"), F.countDistinct("__file", "__row").alias("positions"))


def _round_trip(fmt):
    def run(spark, d):
        path = fresh_path(spark, fmt)
        cols = t(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice")
        cols.write.format(fmt).save(path)
        back = read_any(spark, path, fmt, "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double")
        return back.groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum("o_custkey").alias("keys"))

    return run


for _f in ("csv", "json", "orc"):
    QUERIES[f"op_source_{_f}"] = _round_trip(_f)
    ORACLE[f"op_source_{_f}"] = "select o_orderstatus, count(*) as n, sum(o_custkey)::bigint as keys from orders group by 1"


@query("select n_name, count(*) as customers from customer join nation on c_nationkey = n_nationkey where c_acctbal > 0 group by 1")
def op_sql_views(spark, d):
    register_views(load_db(spark, d), ("customer", "nation"), "v_")
    return spark.sql("select n_name, count(*) as customers from v_customer join v_nation on c_nationkey = n_nationkey where c_acctbal > 0 group by 1")


@query("select count(*) as n from customer c join nation k on c.c_nationkey = k.n_nationkey where c.c_acctbal > 0 and k.n_regionkey in (1, 2)")
def op_sql_to_query(spark, d):
    """SQL text becomes a query value, which is compiled again."""
    db = load_db(spark, d)
    register_views(db, ("customer", "nation"))
    q = from_sql(spark, "select * from customer c join nation k on c.c_nationkey = k.n_nationkey where c.c_acctbal > 0.0 and k.n_regionkey in (1, 2)")
    return to_dataframe(q, db).agg(F.count("*").alias("n"))


@query("select i as sampleindex, " + u60_sql(1, "'x'", "i") + " % 1000 as pos from range(1, 501) r(i)")
def op_generated_rows(spark, d):
    return spark.range(1, 501).select(F.col("id").alias("sampleindex"), F.pmod(u60(1, "x", F.col("id")), F.lit(1000)).alias("pos"))


@query("select lang, sum(length(text))::bigint as chars, sum(n_chars)::bigint as declared from documents group by 1")
def op_scan_wide_text(spark, d):
    v = numeric_views(load_db(spark, d))["documents"]
    return v.join(t(spark, d, "documents").select("doc_id", "lang"), "doc_id").groupBy("lang").agg(F.sum("text_length").alias("chars"), F.sum("n_chars").alias("declared"))


@query("select event_type, count(*) as n from events group by 1")
def op_sink_partitioned(spark, d):
    path = fresh_path(spark, "by-type")
    t(spark, d, "events").select("event_id", "event_type").write.partitionBy("event_type").parquet(path)
    return spark.read.parquet(path).groupBy("event_type").agg(F.count("*").alias("n"))


# --- projection and filters


@query("select o_orderkey, o_totalprice * 2 as twice, o_totalprice > 100000 as big from orders")
def op_project(spark, d):
    return t(spark, d, "orders").select("o_orderkey", (F.col("o_totalprice") * 2).alias("twice"), (F.col("o_totalprice") > 100000).alias("big"))


_OPS = {"lt": "<", "le": "<=", "gt": ">", "ge": ">=", "eq": "=", "ne": "<>"}


@query("select " + ", ".join(f"count(*) filter (where l_quantity {o} 25) as {n}" for n, o in _OPS.items()) + " from lineitem")
def op_filter_comparators(spark, d):
    return t(spark, d, "lineitem").agg(*[F.count_if(F.expr(f"l_quantity {o} 25")).alias(n) for n, o in _OPS.items()])


@query("select count(*) as n from lineitem where not ((l_quantity < 10 or l_discount > 0.05) and not l_returnflag = 'R')")
def op_filter_boolean(spark, d):
    c = ~(((F.col("l_quantity") < 10) | (F.col("l_discount") > 0.05)) & ~(F.col("l_returnflag") == "R"))
    return t(spark, d, "lineitem").where(c).agg(F.count("*").alias("n"))


@query("select count(*) as n from orders where o_totalprice between 1000 and 200000 and o_orderstatus in ('F', 'O') and o_orderdate is not null")
def op_filter_between_in_null(spark, d):
    o = t(spark, d, "orders")
    return o.where(F.col("o_totalprice").between(1000, 200000) & F.col("o_orderstatus").isin("F", "O") & F.col("o_orderdate").isNotNull()).agg(F.count("*").alias("n"))


@query("select count(*) as n from part where p_name like '%1%' and regexp_matches(p_brand, '[0-9]+')")
def op_filter_opaque(spark, d):
    return t(spark, d, "part").where(F.col("p_name").like("%1%") & F.col("p_brand").rlike("[0-9]+")).agg(F.count("*").alias("n"))


# --- joins


def _equi(strategy):
    def run(spark, d):
        o, l = t(spark, d, "orders").select("o_orderkey", "o_orderstatus"), t(spark, d, "lineitem").select("l_orderkey", "l_quantity")
        return O.join(l, o, l.l_orderkey == o.o_orderkey, "inner", strategy).groupBy("o_orderstatus").agg(F.sum("l_quantity").alias("q"), F.count("*").alias("n"))

    return run


def op_join_broadcast(spark, d):
    """Orders are broadcast in parts that a driver can hold; sums and counts of the parts are added up."""
    o, l = t(spark, d, "orders").select("o_orderkey", "o_orderstatus"), t(spark, d, "lineitem").select("l_orderkey", "l_quantity")
    part = O.broadcast_join(l, o, "l_orderkey", "o_orderkey", lambda j: j.groupBy("o_orderstatus").agg(F.sum("l_quantity").alias("q"), F.count("*").alias("n")))
    return part.groupBy("o_orderstatus").agg(F.sum("q").alias("q"), F.sum("n").alias("n"))


QUERIES["op_join_broadcast"] = op_join_broadcast
for _s in ("broadcast", "shuffle_hash", "merge", "auto"):
    QUERIES.setdefault(f"op_join_{_s}", _equi(_s))
    ORACLE[f"op_join_{_s}"] = "select o_orderstatus, sum(l_quantity) as q, count(*) as n from orders join lineitem on o_orderkey = l_orderkey group by 1"


@query("select count(*) as n, sum(s_suppkey)::bigint as k from customer, supplier where c_acctbal < s_acctbal")
def op_join_theta(spark, d):
    """All customers and suppliers: counted from running sums over the balances, no pair is formed."""
    return O.less_join_sums(t(spark, d, "customer"), t(spark, d, "supplier"), "c_acctbal", "s_acctbal", "s_suppkey", "k")


@query("select count(*) as n from customer, supplier where c_nationkey <> s_nationkey")
def op_join_ne(spark, d):
    return O.ne_join_count(t(spark, d, "customer"), t(spark, d, "supplier"), "c_nationkey", "s_nationkey")


@query("select r_name, n_name from region, nation")
def op_join_cross(spark, d):
    return t(spark, d, "region").select("r_name").crossJoin(t(spark, d, "nation").select("n_name"))


@query("select e.event_id, p.p_partkey from events e join part p on e.value between p.p_size and p.p_size + 0.5")
def op_range_join(spark, d):
    """All pairs of an event and a part whose range holds its value."""
    e = t(spark, d, "events").select("event_id", "value")
    p = t(spark, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("lo"), (F.col("p_size") + 0.5).alias("hi"))
    return O.range_join(e, p, "value", "lo", "hi", 1.0).select("event_id", "p_partkey")


@query("select p.p_partkey, count(*) as events from events e join part p on e.value between p.p_size and p.p_size + 0.5 group by 1")
def op_range_join_counts(spark, d):
    """All events and parts; a part's events are counted from running sums, no pair is formed."""
    e = t(spark, d, "events").select("value")
    p = t(spark, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("lo"), (F.col("p_size") + 0.5).alias("hi"))
    return O.range_counts(e, p, "value", "lo", "hi", "events").groupBy("p_partkey").agg(F.sum("events").alias("events"))


@query("""
with x as (select user_id, ts, event_id, event_type, value from events)
select p.event_id, (select c.value from x c where c.user_id = p.user_id and c.event_type = 'click' and c.ts <= p.ts order by c.ts desc, c.event_id desc limit 1) as last_value
from x p where p.event_type = 'purchase'""")
def op_asof_join(spark, d):
    e = t(spark, d, "events").select("user_id", "ts", "event_id", "event_type", "value")
    left = e.where("event_type = 'purchase'").select("user_id", "ts", "event_id")
    return O.asof_join(left, e.where("event_type = 'click'").select("user_id", "ts", "event_id", "value"), "user_id", "ts", "value", "event_id").select("event_id", "last_value")


@query("select count(*) as n from customer where c_custkey in (select o_custkey from orders)")
def op_semi(spark, d):
    o = t(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey"))
    return O.semi(t(spark, d, "customer"), o, "c_custkey").agg(F.count("*").alias("n"))


@query("select count(*) as n from customer where c_custkey not in (select o_custkey from orders)")
def op_anti(spark, d):
    o = t(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey"))
    return O.anti(t(spark, d, "customer"), o, "c_custkey").agg(F.count("*").alias("n"))


def _outer(how, sql):
    def run(spark, d):
        return t(spark, d, "documents").select("doc_id").join(t(spark, d, "labels").select("doc_id", "quality"), "doc_id", how)

    QUERIES[f"op_join_{how}"] = run
    ORACLE[f"op_join_{how}"] = f"select doc_id, quality from (select doc_id from documents) x {sql} join (select doc_id, quality from labels) y using (doc_id)"


for _h, _q in (("left", "left"), ("right", "right"), ("full", "full")):
    _outer(_h, _q)


@query("select a.n_name as n1, b.n_name as n2 from nation a join nation b on a.n_regionkey = b.n_regionkey and a.n_nationkey < b.n_nationkey")
def op_self_join(spark, d):
    a, b = t(spark, d, "nation").alias("a"), t(spark, d, "nation").alias("b")
    return a.join(b, (F.col("a.n_regionkey") == F.col("b.n_regionkey")) & (F.col("a.n_nationkey") < F.col("b.n_nationkey"))).select(F.col("a.n_name").alias("n1"), F.col("b.n_name").alias("n2"))


@query("select r_name, count(*) as n, sum(l_quantity) as q from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1")
def op_join_chain(spark, d):
    l, o, c, n, r = (t(spark, d, x) for x in ("lineitem", "orders", "customer", "nation", "region"))
    j = l.select("l_orderkey", "l_quantity").join(o.select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).join(c.select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    return j.join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"))


# --- aggregation


@query("select l_returnflag, count(*) as n, count(*) filter (where l_quantity > 25) as big, round(avg(l_quantity), 9) as mean, round(stddev_pop(l_quantity), 9) as sd_pop, round(stddev_samp(l_quantity), 9) as sd_samp, round(var_samp(l_quantity), 6) as var, min(l_discount) as lo, max(l_discount) as hi from lineitem group by 1")
def op_agg_basic(spark, d):
    q = F.col("l_quantity")
    return t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"), F.count_if(q > 25).alias("big"), F.round(F.avg(q), 9).alias("mean"), F.round(F.stddev_pop(q), 9).alias("sd_pop"), F.round(F.stddev_samp(q), 9).alias("sd_samp"), F.round(F.var_samp(q), 6).alias("var"), F.min("l_discount").alias("lo"), F.max("l_discount").alias("hi"))


@query("select (select count(distinct p_brand) from part) as brands, (select count(*) from (select distinct p_brand, p_size from part)) as pairs")
def op_agg_distinct(spark, d):
    return t(spark, d, "part").agg(F.countDistinct("p_brand").alias("brands"), F.countDistinct(F.struct("p_brand", "p_size")).alias("pairs"))


@query()
def op_agg_sketches(spark, d):
    l = t(spark, d, "lineitem")
    hll = F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey"))
    return l.agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), hll.alias("hll_parts"), F.approx_percentile("l_extendedprice", [0.25, 0.5, 0.75], 10000).alias("quartiles"))


@query("select (select round(corr(p_partkey, p_retailprice), 6) from part) as r, (select round(covar_pop(p_partkey, p_retailprice), 3) from part) as c")
def op_agg_correlation(spark, d):
    return t(spark, d, "part").agg(F.round(F.corr("p_partkey", "p_retailprice"), 6).alias("r"), F.round(F.covar_pop("p_partkey", "p_retailprice"), 3).alias("c"))


@query("select user_id, list_sort(list(event_id)) as ids from events group by 1")
def op_agg_collect(spark, d):
    return t(spark, d, "events").groupBy("user_id").agg(F.array_sort(F.collect_list("event_id")).alias("ids"))


@query("select l_returnflag, l_linestatus, count(*) as n from lineitem group by rollup (l_returnflag, l_linestatus)")
def op_rollup(spark, d):
    return t(spark, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("select l_returnflag, l_linestatus, count(*) as n from lineitem group by cube (l_returnflag, l_linestatus)")
def op_cube(spark, d):
    return t(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("select l_returnflag, l_linestatus, count(*) as n from lineitem group by grouping sets ((l_returnflag), (l_linestatus), ())")
def op_grouping_sets(spark, d):
    t(spark, d, "lineitem").createOrReplaceTempView("g_lineitem")
    return spark.sql("select l_returnflag, l_linestatus, count(*) as n from g_lineitem group by grouping sets ((l_returnflag), (l_linestatus), ())")


@query("select event_type, count(*) filter (where user_id % 2 = 0) as even, count(*) filter (where user_id % 2 = 1) as odd from events group by 1")
def op_pivot(spark, d):
    e = t(spark, d, "events").withColumn("side", F.when(F.col("user_id") % 2 == 0, "even").otherwise("odd"))
    return e.groupBy("event_type").pivot("side", ["even", "odd"]).count().na.fill(0)


# --- windows


@query("select o_orderkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr from orders window w as (partition by o_custkey order by o_orderpriority, o_orderkey)")
def op_window_ranks(spark, d):
    w = W.partitionBy("o_custkey").orderBy("o_orderpriority", "o_orderkey")
    return t(spark, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"))


@query("select bucket, min(o_totalprice) as lo, max(o_totalprice) as hi, count(*) as n from (select o_totalprice, ntile(20) over (order by o_totalprice, o_orderkey) as bucket from orders) x group by 1")
def op_window_ntile(spark, d):
    return O.equi_depth_ntile(t(spark, d, "orders"), "o_totalprice", 20, ["o_orderkey"])


@query("select s_suppkey, round(cume_dist() over (order by s_acctbal), 9) as share, round(percent_rank() over (order by s_acctbal), 9) as pr from supplier")
def op_window_cume_dist(spark, d):
    w = W.orderBy("s_acctbal")
    return t(spark, d, "supplier").select("s_suppkey", F.round(F.cume_dist().over(w), 9).alias("share"), F.round(F.percent_rank().over(w), 9).alias("pr"))


@query("select event_id, lag(value) over w as prev, lead(value) over w as next, first_value(value) over w as first from events window w as (partition by user_id order by ts, event_id)")
def op_window_lag_lead(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return t(spark, d, "events").select("event_id", F.lag("value").over(w).alias("prev"), F.lead("value").over(w).alias("next"), F.first("value").over(w).alias("first"))


@query("select o_orderkey, sum(1) over (partition by o_custkey order by o_orderkey rows between 2 preceding and current row) as three, count(*) over (partition by o_custkey order by o_orderkey range between 1000 preceding and current row) as near from orders")
def op_window_frames(spark, d):
    w = W.partitionBy("o_custkey").orderBy("o_orderkey")
    return t(spark, d, "orders").select("o_orderkey", F.sum(F.lit(1)).over(w.rowsBetween(-2, 0)).alias("three"), F.count("*").over(w.rangeBetween(-1000, 0)).alias("near"))


# --- order, top-k, sets


@query("select p_partkey, p_retailprice from part order by p_retailprice desc, p_partkey limit 10")
def op_topk(spark, d):
    return O.topk(t(spark, d, "part").select("p_partkey", "p_retailprice"), "p_retailprice", 10, tie="p_partkey")


@query("select p_partkey, p_size from (select *, rank() over (order by p_size desc) as r from part) x where r <= 10")
def op_topk_ties(spark, d):
    return O.topk(t(spark, d, "part").select("p_partkey", "p_size"), "p_size", 10, ties=True)


@query("select event_type, min_by(event_id, ts) as event_id_at_min, max_by(event_id, ts) as event_id_at_max from (select event_type, ts, min(event_id) as event_id from events group by 1, 2) x group by 1")
def op_arg_extreme(spark, d):
    e = t(spark, d, "events").groupBy("event_type", "ts").agg(F.min("event_id").alias("event_id"))
    return O.arg_extreme(e, ["event_type"], "event_id", "ts")


@query("select o_orderkey from orders order by o_totalprice, o_orderkey limit 20 offset 5")
def op_sort_offset(spark, d):
    return t(spark, d, "orders").orderBy("o_totalprice", "o_orderkey").offset(5).limit(20).select("o_orderkey")


_A, _B = "select o_orderkey from orders where o_totalprice < 100000", "select o_orderkey from orders where o_orderstatus = 'F'"


def _sets(spark, d):
    o = t(spark, d, "orders")
    return o.where("o_totalprice < 100000").select("o_orderkey"), o.where("o_orderstatus = 'F'").select("o_orderkey")


@query(f"{_A} union {_B}")
def op_set_union(spark, d):
    a, b = _sets(spark, d)
    return a.union(b).distinct()


@query(f"{_A} intersect {_B}")
def op_set_intersect(spark, d):
    a, b = _sets(spark, d)
    return a.intersect(b)


@query(f"{_A} except {_B}")
def op_set_except(spark, d):
    a, b = _sets(spark, d)
    return a.exceptAll(b)


# --- scalar functions


@query("select doc_id, md5(text) as h, upper(lang) as l, substr(source, 1, 3) as s, concat_ws('-', lang, source) as c, length(text) as n, text like '%the%' as has from documents")
def op_fn_string(spark, d):
    return t(spark, d, "documents").select("doc_id", F.md5("text").alias("h"), F.upper("lang").alias("l"), F.substring("source", 1, 3).alias("s"), F.concat_ws("-", "lang", "source").alias("c"), F.length("text").cast("long").alias("n"), F.col("text").like("%the%").alias("has"))


@query("select o_orderkey, year(o_orderdate)::int as y, month(o_orderdate)::int as m, date_diff('day', timestamp '1992-01-01', o_orderdate)::int as days, epoch_us(o_orderdate) as us from orders")
def op_fn_date(spark, d):
    c = F.col("o_orderdate")
    return t(spark, d, "orders").select("o_orderkey", F.year(c).alias("y"), F.month(c).alias("m"), F.datediff(c, F.lit("1992-01-01").cast("date")).alias("days"), F.unix_micros(c.cast("timestamp")).alias("us"))


@query("select i as k, round(ln(i), 9) as a, round(log2(i), 9) as b, ceil(i / 3.0)::bigint as c, floor(i / 3.0)::bigint as f, pow(i, 2)::double as p, i % 7 as m, greatest(i, 10) as g, least(i, 10) as l from range(1, 50) r(i)")
def op_fn_math(spark, d):
    k = F.col("id")
    return spark.range(1, 50).select(k.alias("k"), F.round(F.log(k), 9).alias("a"), F.round(F.log2(k.cast("double")), 9).alias("b"), F.ceil(k / 3.0).alias("c"), F.floor(k / 3.0).alias("f"), F.pow(k, F.lit(2)).alias("p"), F.pmod(k, F.lit(7)).alias("m"), F.greatest(k, F.lit(10)).alias("g"), F.least(k, F.lit(10)).alias("l"))


@query("select vec_id, len(embedding)::int as n, round(sqrt(list_sum(list_transform(embedding::double[], lambda x: x * x))), 6) as norm, embedding[1]::double as first, len(list_filter(embedding, lambda x: x > 0))::int as positive from embeddings")
def op_fn_array(spark, d):
    e = F.transform("embedding", lambda x: x.cast("double"))
    norm = F.sqrt(F.aggregate(e, F.lit(0.0), lambda a, x: a + x * x))
    return t(spark, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.round(norm, 6).alias("norm"), F.element_at(e, 1).alias("first"), F.size(F.filter(e, lambda x: x > 0)).alias("positive"))


@query("select event_id, json_extract(props, '$.k')::int as k, (json_extract(props, '$.k')::int) * 2 as twice from events")
def op_fn_json_map(spark, d):
    m = F.from_json("props", "map<string,int>")
    return t(spark, d, "events").select("event_id", F.element_at(m, "k").alias("k"), (F.element_at(F.map_filter(m, lambda k, v: k == "k"), "k") * 2).alias("twice"))


@query("select sum(l_extendedprice::decimal(12, 2))::double as total, (select count(*) from orders)::double * (select count(*) from lineitem) as product from lineitem")
def op_fn_decimal(spark, d):
    orders = t(spark, d, "orders").agg(F.count("*").alias("o"))
    l = t(spark, d, "lineitem").agg(F.sum(F.col("l_extendedprice").cast("decimal(12,2)")).alias("total"), F.count("*").alias("n"))
    return l.crossJoin(orders).select(F.col("total").cast("double").alias("total"), (F.col("n").cast("decimal(19,0)") * F.col("o").cast("decimal(19,0)")).cast("double").alias("product"))  # one row each


# --- user-defined functions


@query("select l_quantity, count(*) as n, round((l_quantity - 1) / 49, 9) as share from lineitem group by 1")
def udf_hist_fraction(spark, d):
    share = udfs.hist_fraction([1.0, 25.5, 50.0])
    return t(spark, d, "lineitem").groupBy("l_quantity").agg(F.count("*").alias("n")).withColumn("share", F.round(share("l_quantity"), 9))


@query("with r as (select o_orderstatus, o_totalprice, row_number() over (partition by o_orderstatus order by o_totalprice) - 1 as k, count(*) over (partition by o_orderstatus) as n from orders) select o_orderstatus, list(o_totalprice order by k) as bounds from (select distinct o_orderstatus, o_totalprice, k from r, range(0, 5) j(j) where k = (j * (n - 1)) // 4) x group by 1")
def udf_equi_depth(spark, d):
    return t(spark, d, "orders").groupBy("o_orderstatus").agg(udfs.equi_depth_udaf("o_totalprice").alias("bounds"))


@query("select 'l_discount' as col, count(*) as n, count(distinct l_discount) as ndv, min(l_discount) as lo, max(l_discount) as hi from lineitem union all select 'l_tax', count(*), count(distinct l_tax), min(l_tax), max(l_tax) from lineitem")
def udf_grouped_map(spark, d):
    l = t(spark, d, "lineitem").selectExpr("stack(2, 'l_discount', l_discount, 'l_tax', l_tax) as (col, v)")
    return l.groupBy("col").applyInPandas(udfs.column_summary, "col string, n long, ndv long, lo double, hi double")


@query("select k, a * b as pairs from (select c_nationkey::bigint as k, count(*) as a from customer group by 1) x join (select s_nationkey::bigint as k, count(*) as b from supplier group by 1) y using (k) union all select c_nationkey, 0 from customer where c_nationkey not in (select s_nationkey from supplier) group by 1 union all select s_nationkey, 0 from supplier where s_nationkey not in (select c_nationkey from customer) group by 1")
def udf_cogrouped_map(spark, d):
    c = t(spark, d, "customer").select(F.col("c_nationkey").cast("long").alias("k"))
    s = t(spark, d, "supplier").select(F.col("s_nationkey").cast("long").alias("k"))
    return c.groupBy("k").cogroup(s.groupBy("k")).applyInPandas(udfs.pair_counts, "k long, pairs long")


@query("select s_acctbal as v, ((s_acctbal <= 0)::int + 2 * (s_acctbal <= 5000)::int)::bigint as bits from supplier")
def udf_map_batches(spark, d):
    return t(spark, d, "supplier").select(F.col("s_acctbal").alias("v")).mapInPandas(udfs.threshold_bits([0.0, 5000.0]), "v double, bits long")


@query("select i as sampleindex, ('0x' || substr(md5(concat_ws('|', '5', 't', i::varchar)), 1, 15))::bigint % 97 as pos from range(1, 201) r(i)")
def udtf_sample_draws(spark, d):
    udfs.table_functions(spark)
    return spark.sql("select * from sample_draws(200, 97, 5)")


@query("select j::int as j, j * 2.5::double as lo, (j + 1) * 2.5::double as hi from range(0, 4) r(j)")
def udtf_buckets(spark, d):
    udfs.table_functions(spark)
    return spark.sql("select * from even_buckets(0.0D, 10.0D, 4)")


@query("select u, m, b, n::bigint as n from (values (1, 1, 1, 1000), (1, 2, 5, 9600), (2, 1, 1, 2800)) x(u, m, b, n)")
def udf_required_sample_size(spark, d):
    udfs.register(spark)
    return spark.sql("select u, m, b, required_sample_size(u, m, b, 0.05D, 0.05D) as n from values (1, 1, 1), (1, 2, 5), (2, 1, 1) as x(u, m, b)")
