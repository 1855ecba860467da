"""Streaming queries, run to the end of what has arrived."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from cardest import streaming as S
from cardest.catalog.common import SEED
from cardest.functions.rng import u60_sql
from cardest.sources import load


def _stream(spark, d, twice=False):
    events = load(spark, d, "events")
    path = S.as_files(events.unionByName(events) if twice else events)
    return S.read_events(spark, path, events.schema)


def _name(kind: str) -> str:
    return f"{kind}_{uuid.uuid4().hex[:8]}"


def _windowed(kind):
    def run(spark, d):
        return S.drain(S.windowed(S.prepare(_stream(spark, d), "10 days"), kind), "complete", _name(kind))

    return run


def stream_dedup(spark, d):
    """Every event arrives twice and is kept once."""
    arrivals = S.prepare(_stream(spark, d, twice=True), "60 days").select("at", "event_id", "event_type")
    out = S.drain(S.dedup(arrivals, ["event_id"]), "append", _name("dedup"))
    return out.groupBy("event_type").agg(F.count("*").alias("n"))


def stream_reservoir(spark, d):
    return S.maintain_sample(_stream(spark, d), 200, SEED, "event_id").select("event_id", "event_type")


def stream_drift(spark, d):
    log = S.drift(_stream(spark, d), {"clicks": F.col("event_type") == "click", "early": F.col("event_id") < 2000}, 0.05)
    return spark.createDataFrame(log, "batch long, rows long, alarm boolean, clicks double, early double")


def stream_join_dimension(spark, d):
    """Each batch joined to a table at rest."""
    customers = load(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    out = S.drain(_stream(spark, d).join(customers, "user_id").select("event_id", "c_mktsegment"), "append", _name("joined"))
    return out.groupBy("c_mktsegment").agg(F.count("*").alias("n"))


def stream_stateful_totals(spark, d):
    out = S.drain(S.stateful_totals(_stream(spark, d)), "update", _name("totals"))
    return out.groupBy("event_type").agg(F.max("n").alias("n"))


def stream_append_windows(spark, d):
    """Append mode: windows come out once the watermark has passed them; late rows are dropped."""
    return S.drain(S.windowed(S.prepare(_stream(spark, d), "1 hour"), "tumbling"), "append", _name("closed"))


QUERIES = {f"stream_{k}": _windowed(k) for k in ("tumbling", "sliding", "session")} | {f.__name__: f for f in (stream_dedup, stream_reservoir, stream_drift, stream_join_dimension, stream_stateful_totals, stream_append_windows)}

ORACLE = {
    "stream_tumbling": "select time_bucket(interval '1 hour', ts) as start, time_bucket(interval '1 hour', ts) + interval '1 hour' as stop, event_type, count(*) as n, sum(event_id)::bigint as ids from events group by 1, 2, 3",
    "stream_sliding": "select b as start, b + interval '1 hour' as stop, event_type, count(*) as n, sum(event_id)::bigint as ids from (select *, unnest([time_bucket(interval '30 minutes', ts), time_bucket(interval '30 minutes', ts) - interval '30 minutes']) as b from events) x group by 1, 2, 3",
    "stream_session": """
with g as (select *, case when ts - lag(ts) over (partition by event_type order by ts, event_id) < interval '1 hour' then 0 else 1 end as first from events),
s as (select *, sum(first) over (partition by event_type order by ts, event_id rows unbounded preceding) as session from g)
select min(ts) as start, max(ts) + interval '1 hour' as stop, event_type, count(*) as n, sum(event_id)::bigint as ids from s group by event_type, session""",
    "stream_dedup": "select event_type, count(*) as n from events group by 1",
    "stream_reservoir": f"select event_id, event_type from events order by {u60_sql(SEED, repr('stream'), 'event_id')}, event_id limit 200",
    "stream_join_dimension": "select c_mktsegment, count(*) as n from events join customer on user_id = c_custkey group by 1",
    "stream_append_windows": """
select time_bucket(interval '1 hour', ts) as start, time_bucket(interval '1 hour', ts) + interval '1 hour' as stop, event_type, count(*) as n, sum(event_id)::bigint as ids
from events group by 1, 2, 3 having time_bucket(interval '1 hour', min(ts)) + interval '1 hour' <= (select max(ts) - interval '1 hour' from events)""",
    "stream_stateful_totals": "select event_type, count(*) as n from events group by 1",
}
