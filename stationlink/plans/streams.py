"""Streaming queries with batch twins in SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from stationlink.functions.numbering import uniform
from stationlink.plans import oracles as o
from stationlink.plans.experiments import idents, query
from stationlink.sources import fixtures
from stationlink.streaming import arrivals

_EV = "ev as (select event_id, ts, event_type, event_id % (select count(*) from part) as node_id, value from events)"


def _stream(spark, d):
    return arrivals.as_stream(spark, fixtures.arrivals(spark, d))


# A window is written once the watermark passes its end, so the windows still open at the end of input are left out.
@query("s_window_tumbling", f"with {_EV}, w as (select date_trunc('hour', ts) as start, event_type, count(*) as n from ev group by 1, 2) select strftime(start, '%Y-%m-%d %H') as start, event_type, n from w where start + interval 1 hour <= (select max(ts) from ev)")
def s_window_tumbling(spark, d):
    return arrivals.drain(arrivals.tumbling(_stream(spark, d))).select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "event_type", "n")


@query("s_window_sliding", f"with {_EV}, w as (select start, count(*) as n from (select unnest([date_trunc('hour', ts), date_trunc('hour', ts) - interval 1 hour]) as start from ev) group by 1) select strftime(start, '%Y-%m-%d %H') as start, n from w where start + interval 2 hour <= (select max(ts) from ev)")
def s_window_sliding(spark, d):
    return arrivals.drain(arrivals.sliding(_stream(spark, d))).select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "n")


@query("s_window_session", f"""with {_EV}, g as (select *, case when ts - lag(ts) over (partition by node_id order by ts) < interval 30 minute then 0 else 1 end as fresh from ev),
s as (select *, sum(fresh) over (partition by node_id order by ts rows unbounded preceding) as k from g),
w as (select node_id, k, min(ts) as start, max(ts) as last_ts, count(*) as n from s group by 1, 2)
select node_id, strftime(start, '%Y-%m-%d %H:%M:%S') as start, n from w where last_ts + interval 30 minute <= (select max(ts) from ev)""")
def s_window_session(spark, d):
    return arrivals.drain(arrivals.sessions(_stream(spark, d))).select("node_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


_LATE = o.u("'late:' || event_id") + " < 0.02"


@query("s_late", f"""with {_EV}, kept as (select * from ev where not ({_LATE}) or date_trunc('hour', ts) + interval 1 hour > (select max(ts) - interval 1 hour from ev where not ({_LATE}))),
w as (select date_trunc('hour', ts) as start, event_type, count(*) as n from kept group by 1, 2)
select strftime(start, '%Y-%m-%d %H') as start, event_type, n from w where start + interval 1 hour <= (select max(ts) - interval 1 hour from ev)""")
def s_late(spark, d):
    """Hourly counts with a watermark of one hour, where one row in fifty comes after all others: those of closed hours are left out."""
    rows = fixtures.arrivals(spark, d)
    late = uniform("late", F.col("event_id")) < 0.02
    got = arrivals.drain_parts([rows.where(~late), rows.where(late)], lambda s: arrivals.tumbling(s, late="1 hour"))
    return got.select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "event_type", "n")


@query("s_dedup", f"with {_EV} select node_id, event_type, count(distinct node_id) as n from ev group by 1, 2")
def s_dedup(spark, d):
    return arrivals.drain(arrivals.deduplicated(_stream(spark, d))).groupBy("node_id", "event_type").agg(F.count("*").alias("n"))


@query("s_interval", f"with {_EV} select a.event_id as a_id, b.event_id as b_id from ev a join ev b on a.node_id = b.node_id and b.ts > a.ts and b.ts <= a.ts + interval 20000 minute")
def s_interval(spark, d):
    rows = fixtures.arrivals(spark, d)
    return arrivals.drain(arrivals.interval_join(arrivals.as_stream(spark, rows), arrivals.as_stream(spark, rows), 20000))


_TURN = f"({o.PI2} * {o.u(chr(39) + 'ev:' + chr(39) + ' || event_id')})"


@query("s_static_match", f"""with {o.IDENTS}, {_EV}, g as (select distinct node_id, town, lat, lon, label from st_labels where kind = 'generic'),
a as (select event_id, town, label, lat + value * sin({_TURN}) / 111194.93 as a_lat, lon + value * cos({_TURN}) / (111194.93 * cos(radians(lat))) as a_lon from ev join g using (node_id)),
c as (select a.*, i.ident_id, i.label as r_label, i.lat as b_lat, i.lon as b_lon from a join st_idents i using (town)),
s as (select event_id, ident_id, {o.dist()} as dist_m, {o.ed('label', 'r_label')} as s, 0.5::double as t from c)
select event_id, count(*) as near, sum(((exp(dist_m * (-0.6931471805599453 / 60)) + {o.RESCALED.format(s='s')}) / 2 > 0.5)::int)::bigint as same from s where dist_m <= 1000 group by 1""")
def s_static_match(spark, d):
    got = arrivals.drain(arrivals.matched(_stream(spark, d), idents(spark, d)).select("event_id", "ident_id", "predicted"))
    return got.groupBy("event_id").agg(F.count("*").alias("near"), F.sum("predicted").alias("same"))


@query("s_state", f"with {_EV} select node_id, count(*) as n from ev group by 1")
def s_state(spark, d):
    return arrivals.last_state(_stream(spark, d)).select("node_id", "n")
