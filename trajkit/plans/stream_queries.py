"""Streaming queries: each runs its stream over the events files; the SQL is the batch result."""

from __future__ import annotations

from pyspark.sql import functions as F

from trajkit.plans.base_queries import features_of, register
from trajkit.streaming import live as S

register("st_tumbling", "SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")(lambda s, d: S.run(S.tumbling(S.event_stream(s, d)), "complete"))
register("st_sliding", "SELECT strftime(ts::DATE - k::INTEGER, '%Y-%m-%d') AS start, count(*) AS n FROM events CROSS JOIN range(7) AS r(k) GROUP BY 1")(lambda s, d: S.run(S.sliding(S.event_stream(s, d)), "complete"))
register("st_session", """SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g
  FROM (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 12 HOUR THEN 1 ELSE 0 END AS new FROM events)) GROUP BY user_id, g""")(lambda s, d: S.run(S.sessions(S.event_stream(s, d)), "complete"))
register("st_dedup", "SELECT event_id, user_id FROM events")(lambda s, d: S.run(S.deduplicated(S.event_stream(s, d))))
register("st_state", "SELECT user_id, count(*) AS total, count(DISTINCT ts::DATE) AS active_days FROM events GROUP BY 1")(lambda s, d: S.run(S.user_series(S.event_stream(s, d)), "update", ("user_id",)))
_CLASS = "CASE WHEN t_peak < 15 THEN 'early' ELSE 'late' END"


@register("st_join_static")
def _(s, d):
    classes = features_of(s, d, "user_day", 30).select(F.col("item_id").alias("user_id"), F.expr(_CLASS).alias("class"))
    return S.run(S.scored(S.event_stream(s, d), classes), "complete")


register("st_join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events AS a JOIN events AS b ON a.user_id = b.user_id AND a.event_type = 'purchase' AND b.event_type <> 'purchase' AND b.ts < a.ts AND b.ts >= a.ts - INTERVAL 1 HOUR")(
    lambda s, d: S.run(S.purchases_after(S.event_stream(s, d)))
)
register("st_late")(S.late_rows)
