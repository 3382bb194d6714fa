"""Streams run to their end and held against batch SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..graph.builders import event_items, load
from ..plans import sqlgen as S
from . import live


def _run(transform, mode="append", watermark="1 day"):
    return lambda s, d: live.drained(transform(live.stream(s, live.staged(s, d), watermark)), mode)


def st_dedup(s, d):
    twice = lambda spark, sf: event_items(spark, sf).unionAll(event_items(spark, sf).where("event_id % 10 = 0"))
    events = live.stream(s, live.staged(s, d, table=twice))
    return live.drained(events.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "k"))


def st_static_join(s, d):
    customers = load(s, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return live.drained(live.stream(s, live.staged(s, d)).join(customers, "user_id").select("event_id", "c_mktsegment"))


def st_stream_join(s, d):
    source = live.staged(s, d)
    a = live.stream(s, source).where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("a"))
    b = live.stream(s, source).where("event_type = 'purchase'").select(F.col("user_id").alias("u"), F.col("ts").alias("t"), F.col("event_id").alias("b"))
    return live.drained(a.join(b, F.expr("user_id = u and t >= ts and t <= ts + interval 12 hours")).select("a", "b"))


def st_watermark_late(s, d):
    """Events dated long before their arrival: in the first files they pass, in the last they are behind the watermark and dropped."""
    def shuffled(spark, sf):
        e = event_items(spark, sf)
        return e.select("event_id", "user_id", F.when(F.col("event_id") % 50 == 0, F.col("ts") - F.expr("interval 400 days")).otherwise(F.col("ts")).alias("ts"), "k", F.col("ts").alias("arrival"))

    events = shuffled(s, d)
    path = live.scratch(s, "late-in")
    for lo, hi in ((0.0, 0.3), (0.3, 0.6), (0.6, 1.01)):  # three files by arrival; lateness counts from the batch before the last
        ends = events.agg(F.min("arrival").alias("a"), F.max("arrival").alias("z"))
        at = (F.unix_micros("arrival") - F.unix_micros("a")) / (F.unix_micros("z") - F.unix_micros("a"))
        events.crossJoin(ends).where((at >= lo) & (at < hi)).select("event_id", "user_id", "ts", "k").coalesce(1).write.mode("append").parquet(path)
    source = (path, "event_id long, user_id long, ts timestamp, k long")
    return live.drained(live.stream(s, source, "1 day").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "k"))


def st_pair_counts(s, d):
    pairs = live.drained(live.pair_counts(live.stream(s, live.staged(s, d))))
    return pairs.groupBy("a", "b").agg(F.count("*").alias("n"))


def st_state_sessions(s, d):
    """Closed sessions from state; those still open at the end are not given."""
    return live.drained(live.open_sessions(live.stream(s, live.staged(s, d))))


def st_available_now(s, d):
    """All rows once, in several batches, then again from the same checkpoint: nothing new."""
    return live.drained(live.stream(s, live.staged(s, d), None).select("event_id", "user_id", "k"))


QUERIES = {
    "st_tumbling": _run(live.tumbling, "complete"),
    "st_sliding": _run(live.sliding, "complete"),
    "st_session": _run(live.sessions, "complete"),
    "st_dedup": st_dedup,
    "st_static_join": st_static_join,
    "st_stream_join": st_stream_join,
    "st_watermark_late": st_watermark_late,
    "st_pair_counts": st_pair_counts,
    "st_state_sessions": st_state_sessions,
    "st_available_now": st_available_now,
    "st_foreach_topk": lambda s, d: live.live_top(s, live.staged(s, d), 2, 5),
}
_K = "(props->>'$.k')::bigint"
ORACLES = {
    "st_tumbling": f"select date_trunc('day', ts)::timestamp as start, {_K} as k, count(*) as n, round(sum(value), 4) as total from events group by all",
    "st_sliding": "select (date_trunc('day', ts) - i * interval 1 day)::timestamp as start, count(*) as n from events, range(0, 7) t(i) group by 1",
    "st_session": "select user_id, min(ts) as start, count(*) as n from (select *, sum(s) over (partition by user_id order by ts, event_id rows unbounded preceding) as no from (select *, case when epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts, event_id) < 21600000000 then 0 else 1 end as s from events)) group by user_id, no",
    "st_dedup": f"select event_id, {_K} as k from events",
    "st_static_join": "select event_id, c_mktsegment from events join customer on c_custkey = user_id",
    "st_stream_join": "select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and a.event_type = 'view' and b.event_type = 'purchase' and b.ts between a.ts and a.ts + interval 12 hour",
    "st_watermark_late": f"select event_id, {_K} as k from events, (select epoch_us(min(ts)) as a, epoch_us(max(ts)) as z from events) where event_id % 50 <> 0 or (epoch_us(ts) - a) / (z - a) < 0.6",
    "st_pair_counts": f"with e as (select user_id, ts, {_K} as k from events) select x.k as a, y.k as b, count(*) as n from e x join e y on x.user_id = y.user_id and x.k < y.k and y.ts between x.ts - interval 6 hour and x.ts + interval 6 hour group by all",
    "st_available_now": f"select event_id, user_id, {_K} as k from events",
    "st_foreach_topk": S.path_sql("sessions", 2, 5, edges=S._cooccur(f"select user_id || ':' || ts::date as session, {_K} as item from events", S._WEIGHT["dice"], 0.0) + ", " + S._PLAIN),
}
