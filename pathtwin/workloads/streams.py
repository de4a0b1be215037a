"""Streaming workloads on ``events``."""

from __future__ import annotations

from pyspark.sql import functions as F

from pathtwin.sources.io import read_table
from pathtwin.streaming import windows as S

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def _stream(spark, sf_dir):
    return S.event_stream(spark, f"{sf_dir}/event[s].parquet")


for _kind in ("tumbling", "sliding", "session"):
    QUERIES[f"op_stream_{_kind}"] = lambda spark, sf_dir, k=_kind: S.drained(S.windowed(_stream(spark, sf_dir), k))
ORACLES["op_stream_tumbling"] = "SELECT date_trunc('day', ts) AS start, date_trunc('day', ts) + INTERVAL 1 DAY AS stop, event_type, count(*) AS n FROM events GROUP BY ALL"
ORACLES["op_stream_sliding"] = (
    "WITH h AS (SELECT date_trunc('day', ts) + CASE WHEN hour(ts) >= 12 THEN INTERVAL 12 HOUR ELSE INTERVAL 0 HOUR END AS a, event_type FROM events), "
    "w AS (SELECT a AS start, event_type FROM h UNION ALL SELECT a - INTERVAL 12 HOUR, event_type FROM h) SELECT start, start + INTERVAL 1 DAY AS stop, event_type, count(*) AS n FROM w GROUP BY ALL"
)
ORACLES["op_stream_session"] = (
    "WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS new FROM events), "
    "k AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM g) "
    "SELECT min(ts) AS start, max(ts) + INTERVAL 6 HOUR AS stop, user_id, count(*) AS n FROM k GROUP BY user_id, s"
)
QUERIES["op_stream_dedup"] = lambda spark, sf_dir: S.drained(S.without_repeats(_stream(spark, sf_dir)), "append").select("event_id", "user_id")
ORACLES["op_stream_dedup"] = "SELECT DISTINCT event_id, user_id FROM events"
QUERIES["op_stream_state"] = lambda spark, sf_dir: S.drained(S.flow_state(_stream(spark, sf_dir)), "append")
ORACLES["op_stream_state"] = "SELECT DISTINCT user_id, coalesce(lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id), 'entry') || '>' || event_type AS edge FROM events"
QUERIES["flow_sessions_stream"] = lambda spark, sf_dir: S.drained(S.session_sets(_stream(spark, sf_dir)))


def op_stream_late(spark, sf_dir):
    """Every twentieth event, if ten days older than the newest, arrives after all others: dropped and counted."""
    events = read_table(spark, sf_dir, "events")
    newest = events.agg(F.max("ts").alias("ts")).first()["ts"]
    old = F.col("ts") < F.lit(newest).cast("timestamp_ntz") - F.make_dt_interval(F.lit(10)) if newest else F.lit(False)
    return S.late_counts(events, (F.col("event_id") % 20 == 0) & old)


QUERIES["op_stream_late"] = op_stream_late
ORACLES["op_stream_late"] = (
    "WITH e AS (SELECT date_trunc('day', ts) AS start, event_type, event_id % 20 = 0 AND ts < (SELECT max(ts) FROM events) - INTERVAL 10 DAY AS late FROM events) "
    "SELECT CAST(start AS TIMESTAMP) AS start, event_type, count(*) FILTER (NOT late) AS n, count(*) FILTER (late) AS n_late FROM e GROUP BY ALL"
)
