"""Batch twins of the streaming operators."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..streaming import telemetry as S
from ..tables import load
from .registry import query

_NTZ = "timestamp_ntz"


@query("SELECT date_trunc('hour', ts) AS start, count(*) AS n, round(sum(value), 4) AS units FROM events GROUP BY 1")
def st_tumbling(spark, sf_dir):
    return S.tumbling(load(spark, sf_dir, "events", event_time=True)).withColumn("start", F.col("start").cast(_NTZ))


@query("""WITH e AS (SELECT *, to_timestamp(floor(epoch(ts) / 900) * 900 - k * 900)::timestamp AS start FROM events, range(4) t(k))
SELECT start, count(*) FILTER (event_type = 'error') AS faults, count(*) AS n FROM e WHERE epoch(ts) < epoch(start) + 3600 GROUP BY 1""")
def st_sliding(spark, sf_dir):
    return S.sliding_faults(load(spark, sf_dir, "events", event_time=True)).withColumn("start", F.col("start").cast(_NTZ))


@query("""WITH e AS (SELECT user_id, ts, event_id, epoch(ts) - lag(epoch(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS d FROM events WHERE event_type = 'error'),
r AS (SELECT *, sum(CASE WHEN d IS NULL OR d >= 86400 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS run FROM e)
SELECT user_id, min(ts) AS "begin", max(ts) + INTERVAL 1 DAY AS "end", count(*) AS faults FROM r GROUP BY user_id, run""")
def st_session(spark, sf_dir):
    told = S.sessions(load(spark, sf_dir, "events", event_time=True), "1 day")
    return told.withColumns({"begin": F.col("begin").cast(_NTZ), "end": F.col("end").cast(_NTZ)})
