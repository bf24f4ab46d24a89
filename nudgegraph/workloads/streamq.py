"""Queries that run streams over the event table and keep what they give."""

from __future__ import annotations

from pyspark.sql import functions as F

from nudgegraph.sources.networks import table
from nudgegraph.streaming import online
from nudgegraph.workloads import sql


def _stream(spark, sf_dir, parts=3, late=False):
    return online.stream_actions(spark, online.split_by_time(spark, table(spark, sf_dir, "events"), parts, late))


def _us(column):
    return F.unix_micros(column).alias(column)


def _windows(build, *keys):
    def query(spark, sf_dir):
        rows, _ = online.drain(build(_stream(spark, sf_dir)), "update")
        return online.latest(rows, *keys).withColumn("start", F.unix_micros("start"))

    return query


def _sessions(spark, sf_dir):
    rows, _ = online.drain(online.sessions(_stream(spark, sf_dir, 1)), "complete")
    return rows.select("actor", _us("start"), "n")


def _dedup(spark, sf_dir):
    rows, _ = online.drain(online.deduplicated(_stream(spark, sf_dir)))
    return rows.agg(F.count("*").alias("n"))


def _interval(spark, sf_dir):
    path = online.split_by_time(spark, table(spark, sf_dir, "events"), 2)
    rows, _ = online.drain(online.hits(online.stream_actions(spark, path), online.stream_actions(spark, path)))
    return rows.select("src", "dst", "action", _us("at"))


def _late(spark, sf_dir):
    rows, reports = online.drain(online.tumbling(_stream(spark, sf_dir, 3, True), "1 hour"), "update")
    on_time = online.latest(rows, "start").agg(F.sum("n").alias("n"))
    return on_time


def _probabilities(spark, sf_dir):
    first, _ = online.drain(online.first_actions(_stream(spark, sf_dir)), "update")
    first = first.groupBy("actor", "action").agg(F.min("ts").alias("ts"))
    met = online.hits(first, first)
    return online.probabilities(first, met).select("src", "dst", F.round("p", 6).alias("p"))


def _first_seen(spark, sf_dir):
    rows, _ = online.drain(online.first_seen(_stream(spark, sf_dir)))
    return rows.select("actor", "action", _us("ts"))


def _static(spark, sf_dir):
    """Actions a nation, of actors that the table of customers knows."""
    customer = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("actor"), F.col("c_nationkey").alias("nation"))
    counted = online.with_known(_stream(spark, sf_dir), customer).groupBy("nation").agg(F.count("*").alias("n"))
    return online.latest(online.drain(counted, "update")[0], "nation")


QUERIES = {
    "stream_static_join": _static,
    "stream_tumbling": _windows(online.tumbling, "start"), "stream_sliding": _windows(online.sliding, "start"), "stream_session": _sessions, "stream_dedup": _dedup,
    "stream_interval_join": _interval, "stream_late_rows": _late, "stream_probabilities": _probabilities, "stream_first_seen": _first_seen,
}

_ACT = "(select ts, user_id as actor, event_type || '|' || props as action from events)"
ORACLES = {
    "stream_static_join": "select c_nationkey as nation, count(*) as n from events join customer on c_custkey = user_id group by c_nationkey",
    "stream_tumbling": "select epoch_us(time_bucket(interval '1 day', ts, timestamp '1970-01-01')) as start, count(*) as n from events group by 1",
    "stream_sliding": "select epoch_us(time_bucket(interval '6 hours', ts, timestamp '1970-01-01') - interval '6 hours' * k) as start, count(*) as n from events, range(4) r(k) group by 1",
    "stream_session": """select actor, epoch_us(min(ts)) as start, count(*) as n from (select actor, ts, sum(new_) over (partition by actor order by ts rows unbounded preceding) as g from
      (select user_id as actor, ts, case when ts >= lag(ts) over (partition by user_id order by ts) + interval '30 minutes' then 1 else 0 end as new_ from events)) group by actor, g""",
    "stream_dedup": f"select count(*) as n from (select distinct * from {_ACT})",
    "stream_interval_join": f"select u.actor as src, v.actor as dst, u.action, epoch_us(v.ts) as at from {_ACT} u join {_ACT} v on u.action = v.action and u.actor <> v.actor and v.ts > u.ts and v.ts <= u.ts + interval '6 hours'",
    "stream_late_rows": "select (count(*) filter (ts >= (select min(ts) from events) + interval '1 hour'))::bigint as n from events",
    "stream_probabilities": f"select src, dst, round(p, 6) as p from ({sql.events(6, 1.0)})",
    "stream_first_seen": f"select actor, action, epoch_us(min(ts)) as ts from {_ACT} group by actor, action",
}
