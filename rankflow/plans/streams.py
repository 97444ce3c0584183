"""Queries that run a stream to its end and return what it wrote."""

from __future__ import annotations

from rankflow.plans.queries import Registry
from rankflow.streaming import edges as st


def add(r: Registry) -> None:
    watched = lambda s, d: st.with_watermark(st.event_stream(s, d))
    # the last window of a watermarked stream stays open
    closed = "WHERE window_start + INTERVAL {w} <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR"
    r.add("stream_tumbling", lambda s, d: st.drained(st.window_counts(watched(s, d))), "SELECT * FROM (SELECT date_trunc('day', ts) AS window_start, count(*) AS events FROM events GROUP BY 1) " + closed.format(w="1 DAY"))
    r.add("stream_sliding", lambda s, d: st.drained(st.window_counts(watched(s, d), "sliding")), "SELECT * FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts) - k * INTERVAL 6 HOUR AS window_start, count(*) AS events FROM events, range(4) AS t(k) GROUP BY 1) " + closed.format(w="1 DAY"))
    gaps = "SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 2 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)"
    sessions = f"SELECT user_id, min(ts) AS window_start, max(ts) + INTERVAL 2 HOUR AS stop, count(*) AS events FROM (SELECT user_id, ts, sum(opens) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM ({gaps})) GROUP BY user_id, k"
    r.add("stream_session", lambda s, d: st.drained(st.window_counts(watched(s, d), "session")), f"SELECT window_start, user_id, events FROM ({sessions}) WHERE stop <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR")
    r.add("stream_dedup", lambda s, d: st.drained(st.with_watermark(st.edge_stream(st.event_stream(s, d)), "60 days").dropDuplicates(["src", "dst"]).select("src", "dst")), "SELECT DISTINCT 'u' || user_id AS src, event_type || ':' || json_extract_string(props, '$.k') AS dst FROM events")
    bought = "SELECT a.user_id, a.event_id AS first_id, b.event_id AS then_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'"
    r.add("stream_interval_join", lambda s, d: st.drained(st.viewed_then_bought(st.event_stream(s, d))), bought)
