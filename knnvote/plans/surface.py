"""DuckDB SQL of the queries over events and runs: windows in time, joins in time, JSON, set operations, roll-ups."""

from __future__ import annotations

TUMBLING = "SELECT user_id, strftime(date_trunc('day', ts)::TIMESTAMP, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS events, max(value) AS largest FROM events GROUP BY 1, 2"
SLIDING = "SELECT event_type, strftime(b - to_hours(6 * i), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS events, max(value) AS largest FROM (SELECT event_type, value, time_bucket(INTERVAL 6 HOUR, ts) AS b FROM events), range(4) r(i) GROUP BY 1, 2"
SESSION = """
WITH s AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 2 HOUR THEN 0 ELSE 1 END AS opens FROM events),
n AS (SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nth FROM s)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS events, max(value) AS largest FROM n GROUP BY user_id, nth
"""
AS_OF = "SELECT p.event_id, p.user_id, v.event_id AS last_event_id, v.value AS last_value FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts"
FOLLOWED = "SELECT a.user_id, a.event_id AS first_id, b.event_id AS then_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'"
JSON = "SELECT event_type, sum(k)::BIGINT AS total, count(k) AS known FROM (SELECT event_type, regexp_extract(props, '\"k\": *(-?[0-9]+)', 1)::BIGINT AS k FROM events) GROUP BY 1"
SETS = "{both} SELECT kind, qid, id FROM (SELECT 'found' AS kind, qid, id FROM (SELECT qid, id FROM knn INTERSECT SELECT qid, id FROM truth) UNION ALL SELECT 'missed', qid, id FROM (SELECT qid, id FROM truth EXCEPT SELECT qid, id FROM knn))"
