"""Batch twins of the streaming operators; tests hold the streams against them."""

from __future__ import annotations

from pyspark.sql import functions as F

from clipforge.sources import tables as T
from clipforge.streaming import telemetry as S

from .media import SQL_CHECKS
from .sqlviews import using


def ev(s, d):
    return T.load(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


QUERIES = {
    "stream_gate_batch": lambda s, d: S.stream_gate(T.media_meta(s, d)).select("media_id"),
    "tumbling_phase": lambda s, d: S.stream_phase(ev(s, d), "1 day"),
    "sliding_phase": lambda s, d: S.stream_phase(ev(s, d), "2 hours", "1 hour"),
    "session_user": lambda s, d: S.stream_phase(ev(s, d), "", gap="3 hours"),
    "handoff_batch": lambda s, d: ev(s, d).filter("event_type = 'view'").select("user_id", F.col("ts").alias("made_at"), F.col("event_id").alias("made")).join(
        ev(s, d).filter("event_type = 'click'").select(F.col("user_id").alias("who"), F.col("ts").alias("asked_at"), F.col("event_id").alias("asked")), F.expr("user_id = who and made_at <= asked_at and made_at >= asked_at - interval 30 minutes")).select("made", "asked"),
}
_AG = "event_type, count(*) as n, cast(sum(cast(value as decimal(18,2))) as double) as ms"
ORACLES = {
    "stream_gate_batch": using("media_meta", sql=f"select media_id from media_meta where {' and '.join(f'({c})' for c in SQL_CHECKS.values())}"),
    "tumbling_phase": f"select (epoch_us(ts) // 86400000000) * 86400000000 as start_us, (epoch_us(ts) // 86400000000 + 1) * 86400000000 as end_us, {_AG} from events group by 1, 2, event_type",
    "sliding_phase": f"select (epoch_us(ts) // 3600000000 - k) * 3600000000 as start_us, (epoch_us(ts) // 3600000000 - k + 2) * 3600000000 as end_us, {_AG} from events, (values (0), (1)) v(k) group by 1, 2, event_type",
    "session_user": """with g as (select *, coalesce(epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts, event_id) >= 10800000000, true) as fresh from events), s as (select *, sum(cast(fresh as bigint)) over (partition by user_id order by ts, event_id rows unbounded preceding) as k from g)
      select min(epoch_us(ts)) as start_us, max(epoch_us(ts)) + 10800000000 as end_us, user_id, count(*) as n, cast(sum(cast(value as decimal(18,2))) as double) as ms from s group by user_id, k""",
    "handoff_batch": "select a.event_id as made, b.event_id as asked from events a join events b on a.user_id = b.user_id and a.event_type = 'view' and b.event_type = 'click' and a.ts <= b.ts and a.ts >= b.ts - interval 30 minutes",
}
