"""Queries over streams: the stream's output, with batch SQL where the two must agree."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..streaming import events
from .core import SQL_ROWS

QUERIES = {
    "stream_tumbling": lambda spark, sf_dir: events.tumbling(spark, sf_dir)[0].select(F.unix_seconds("start").alias("start"), "event_type", "n", "mean"),
    "stream_sliding": lambda spark, sf_dir: events.sliding(spark, sf_dir)[0].select(F.unix_seconds("start").alias("start"), "event_type", "n", "mean"),
    "stream_session": lambda spark, sf_dir: events.sessions(spark, sf_dir)[0].select("user_id", F.unix_micros("start").alias("start"), F.unix_micros("end").alias("end"), "n"),
    "stream_watermark_late": events.late,
    "stream_dedup": events.deduplicated,
    "stream_stream_join": lambda spark, sf_dir: events.view_to_click(spark, sf_dir)[0],
    "stream_static_join": events.search_arrivals,
    "stream_stateful_seeds": lambda spark, sf_dir: events.seeds_as_state(spark, sf_dir)[0].select("id", F.round("de", 6).alias("de"), F.round("ds", 6).alias("ds")),
    "stream_insert_waves": events.grown_recall,
}

_MEAN = "(SELECT list(v ORDER BY k) FROM (SELECT k, avg({c}[k]) AS v FROM w, (SELECT unnest(range(1, {n} + 1)) AS k) GROUP BY k))"

ORACLES = {
    "stream_stateful_seeds": f"""WITH {SQL_ROWS["event_stream"]}, m AS (SELECT {_MEAN.format(c="e", n=8)} AS me, {_MEAN.format(c="s", n=2)} AS ms),
        d AS (SELECT id, list_distance(e, me) AS de, list_distance(s, ms) AS ds FROM w, m)
        SELECT id, round(de, 6) AS de, round(ds, 6) AS ds FROM d a WHERE NOT EXISTS (SELECT 1 FROM d b WHERE b.de >= a.de AND b.ds >= a.ds AND (b.de > a.de OR b.ds > a.ds OR b.id < a.id))""",
    "stream_tumbling": "SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS start, event_type, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY ALL",
    "stream_sliding": "SELECT CAST(s AS BIGINT) AS start, event_type, count(*) AS n, round(avg(value), 6) AS mean FROM (SELECT *, unnest([floor(epoch(ts) / 21600) * 21600 - 21600 * k for k in [0, 1, 2, 3]]) AS s FROM events) GROUP BY ALL",
    "stream_session": """WITH g AS (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 8 HOUR THEN 0 ELSE 1 END AS new FROM events),
        s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g),
        w AS (SELECT user_id, min(ts) AS a, max(ts) + INTERVAL 8 HOUR AS b, count(*) AS n FROM s GROUP BY user_id, k)
        SELECT user_id, epoch_us(a) AS start, epoch_us(b) AS "end", n FROM w WHERE b < (SELECT max(ts) FROM events) - INTERVAL 1 HOUR""",
    "stream_dedup": "SELECT event_id, event_type FROM events",
    "stream_stream_join": "SELECT v.event_id AS view_id, c.event_id AS click_id FROM events v JOIN events c ON v.user_id = c.user_id AND v.event_type = 'view' AND c.event_type = 'click' AND c.ts >= v.ts AND c.ts <= v.ts + INTERVAL 1 HOUR",
}
