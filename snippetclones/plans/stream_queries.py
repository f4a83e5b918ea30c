"""Registered streaming queries, held against their batch forms in SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..sources import segment as seg
from ..streaming import events as E
from .registry import query

_H = "md5(concat_ws('#', event_type, props))"
_SIZES = f"SELECT {_H} AS h, count(*) AS size FROM events GROUP BY 1"


@query("h:s size:l", _SIZES)
def stream_cmw_counts(s, d):
    return E.cmw_counts(s, d)


@query("start:l event_type:s n:l", "SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(s, d):
    return E.tumbling(s, d)


@query("start:l event_type:s n:l", "SELECT start, event_type, count(*) AS n FROM (SELECT event_type, unnest(range(q - 2700000000, q + 1, 900000000)) AS start FROM (SELECT event_type, epoch_us(time_bucket(INTERVAL 15 MINUTE, ts)) AS q FROM events)) GROUP BY 1, 2")
def stream_sliding(s, d):
    return E.tumbling(s, d, "15 minutes")


@query("start:l user_id:l n:l", "SELECT min(t) AS start, user_id, count(*) AS n FROM (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY t, event_id) AS k FROM (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY user_id ORDER BY t, event_id) < 1800000000 THEN 0 ELSE 1 END AS f FROM (SELECT event_id, user_id, epoch_us(ts) AS t FROM events))) GROUP BY user_id, k")
def stream_session(s, d):
    return E.sessions(s, d)


@query("start:l n:l")
def stream_watermark_late(s, d):
    return E.late_rows(s, d)


@query("event_id:l user_id:l", "SELECT event_id, user_id FROM events")
def stream_dedup(s, d):
    return E.dedup(s, d)


@query("event_id:l size:l", f"SELECT event_id, size FROM (SELECT event_id, {_H} AS h FROM events) JOIN ({_SIZES}) USING (h) WHERE size >= 2")
def stream_static_join(s, d):
    known = seg.table(s, d, "events").groupBy(F.md5(F.expr(E.SNIPPET)).alias("h")).agg(F.count("*").alias("size")).where("size >= 2")
    return E.static_join(s, d, known)


@query("a:l b:l", "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON concat_ws('#', x.event_type, x.props) = concat_ws('#', y.event_type, y.props) AND x.user_id <> y.user_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 10 MINUTE")
def stream_stream_join(s, d):
    return E.stream_join(s, d)


@query("h:s first_user:l size:l", f"SELECT {_H} AS h, arg_min(user_id, (ts, event_id)) AS first_user, count(*) AS size FROM events GROUP BY 1")
def stream_state(s, d):
    return E.first_seen(s, d)


@query("h:s size:l", _SIZES)
def stream_foreach_batch(s, d):
    return E.upsert(s, d)
