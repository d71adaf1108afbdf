"""Streaming queries of the registry."""

from __future__ import annotations

from ..sources import graphs as G
from ..streaming import events as S
from .oracles import TRI, base
from .queries import add

add("stream_tumbling", "SELECT CAST(epoch(time_bucket(INTERVAL 1 HOUR, ts)) AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")(S.tumbling)
add("stream_sliding", "SELECT start, count(*) AS n FROM (SELECT unnest([CAST(epoch(time_bucket(INTERVAL 1 HOUR, ts)) AS BIGINT), CAST(epoch(time_bucket(INTERVAL 1 HOUR, ts)) AS BIGINT) - 3600]) AS start FROM events) GROUP BY start")(S.sliding)
add("stream_session", "SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n FROM (SELECT user_id, ts, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS b FROM events)) GROUP BY user_id, g")(S.sessions)
_LATE = "WITH h AS (SELECT (CAST(floor(epoch(min(ts))) AS BIGINT) + CAST(floor(epoch(max(ts))) AS BIGINT)) // 2 AS half FROM events), k AS (SELECT ts FROM events, h WHERE NOT (event_id % 10 = 0 AND floor(epoch(ts)) < half)), w AS (SELECT max(ts) - INTERVAL 2 HOUR AS mark FROM k)"
add("stream_late_drop", _LATE + " SELECT CAST(epoch(time_bucket(INTERVAL 1 HOUR, ts)) AS BIGINT) AS start, count(*) AS n FROM k, w GROUP BY time_bucket(INTERVAL 1 HOUR, ts), mark HAVING time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR <= mark")(S.late_drop)
add("stream_dedup", "SELECT DISTINCT event_id, user_id FROM events")(S.deduplicated)
add("stream_copresence_join", "SELECT a.user_id AS u, b.user_id AS v, count(*) AS n FROM events a JOIN events b ON a.event_type = b.event_type AND a.user_id <> b.user_id AND b.ts >= a.ts AND b.ts < a.ts + INTERVAL 10 MINUTE GROUP BY ALL")(S.copresence)
add("stream_incremental_edges", base("user_copresence") + " SELECT src, dst FROM edges")(S.incremental_edges)
add("stream_triangle_delta", base("affinity", TRI) + " SELECT CAST(greatest((a + b) % 3, (a + c) % 3, (b + c) % 3) AS INTEGER) AS batch, count(*) AS new FROM tri GROUP BY ALL")(lambda s, d: S.triangle_delta(s, G.graph(s, d).edges))
add("stream_user_degree", "SELECT user_id, count(DISTINCT nbr) AS d FROM (SELECT a.user_id, b.user_id AS nbr FROM events a JOIN events b ON a.event_type = b.event_type AND a.user_id <> b.user_id AND abs(epoch_us(b.ts) - epoch_us(a.ts)) < 600000000) GROUP BY user_id")(S.user_degree)
