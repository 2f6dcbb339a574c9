"""Streaming queries, each equal to a batch result."""

from __future__ import annotations

from pyspark.sql import functions as F

from beamrank.plans.registry import query
from beamrank.sources.tables import table
from beamrank.streaming import streams


@query("stream_tumbling", "select date_trunc('day', ts)::timestamp as start, event_type, count(*) as n, sum(value::decimal(18,2))::double as v from events group by 1, 2")
def stream_tumbling(spark, d):
    return streams.finished(streams.tumbling(streams.read_events(spark, d)), "complete")


@query("stream_sliding", "select s as start, count(*) as n from (select unnest([time_bucket(interval 12 hours, ts), time_bucket(interval 12 hours, ts) - interval 12 hours]) as s from events) group by 1")
def stream_sliding(spark, d):
    return streams.finished(streams.sliding(streams.read_events(spark, d)), "complete")


@query("stream_session", """with g as (select user_id, ts, case when ts < lag(ts) over w + interval 30 minutes then 0 else 1 end as new from events window w as (partition by user_id order by ts)),
s as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from g)
select user_id, min(ts) as start, count(*) as n from s group by user_id, k""")
def stream_session(spark, d):
    return streams.finished(streams.sessions(streams.read_events(spark, d)), "complete")


@query("stream_dedup", "select distinct user_id, event_type from events")
def stream_dedup(spark, d):
    return streams.finished(streams.deduplicated(streams.read_events(spark, d), "user_id", "event_type"), "append")


@query("stream_static_join", "select c_mktsegment, count(*) as n from events join customer on user_id = c_custkey group by 1")
def stream_static_join(spark, d):
    customers = table(spark, d, "customer").select("c_custkey", "c_mktsegment")
    return streams.finished(streams.with_static(streams.read_events(spark, d), customers, F.expr("user_id = c_custkey"), "c_mktsegment"), "complete")


@query("stream_late", """select date_trunc('day', ts)::timestamp as start, count(*) as n from events where ts >= timestamp '2024-01-15' group by 1
having date_trunc('day', min(ts)) + interval 1 day <= (select max(ts) from events) - interval 1 hour""")
def stream_late(spark, d):
    return streams.late_rows(spark, d)


@query("stream_state", "select user_id, count(*) filter (value >= 50) as accepted, count(*) filter (value >= 50 and event_type = 'purchase') as right_ones from events group by user_id")
def stream_state(spark, d):
    return streams.finished(streams.running_precision(streams.read_events(spark, d)), "update")
