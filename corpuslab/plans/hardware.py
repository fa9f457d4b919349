"""Queries on architecture, run and telemetry."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import hwmodel as H
from ..tables import load
from .registry import query

_ARCH = "(VALUES (18, 2048, 16, 8, 128, 6144, 65536)) a(l, d, h, k, hd, f, v)"
_N = "(v * d + l * (2 * d * hd * (h + k) + 3 * d * f + 2 * d + 2 * hd) + d)"


@query(f"""SELECT unnest(['embedding', 'attention_qo', 'attention_kv', 'ffn', 'norms', 'total']) AS component,
unnest([v * d, l * 2 * d * h * hd, l * 2 * d * k * hd, l * 3 * d * f, l * (2 * d + 2 * hd) + d, {_N}])::bigint AS params FROM {_ARCH}""")
def hw_param_table(spark, sf_dir):
    return H.param_table(H.arch_frame(spark))


@query(f"SELECT round(100 * 6.0 * {_N} * 68052 / 989e12, 3) AS mfu_percent, round(100 * (6.0 * {_N} + 12.0 * l * d * 4096) * 68052 / 989e12, 1) AS with_attention_percent, round(6.0 * {_N} * 68052 / 989e12 / 0.031, 1) AS gain FROM {_ARCH}")
def hw_mfu(spark, sf_dir):
    run = H.Run()
    return spark.createDataFrame([(round(100 * H.mfu(), 3), round(100 * H.mfu(include_attention=True), 1), round(H.mfu() / run.first_mfu, 1))], "mfu_percent double, with_attention_percent double, gain double")


@query("SELECT round(150e9 / 2097152, 1) AS steps, 512.0::double AS sequences_per_step, round(150e9 / (68052 * 8) / 3600, 2) AS hours_per_gpu_rate, round(150e9 / 68052 / 3600, 2) AS hours_per_node_rate")
def hw_run_plan(spark, sf_dir):
    return H.run_plan(spark)


@query("""WITH r AS (SELECT user_id, (epoch_us(max(ts)) - epoch_us(min(ts)))::double / 3.6e9::double AS hours, sum(value::decimal(18, 4))::double AS billions FROM events GROUP BY user_id)
SELECT user_id, round(2500.0::double / nullif(hours, 0), 2) AS per_node_hour, round(2500.0::double / nullif(hours, 0) / 8, 2) AS per_gpu_hour, round(2500.0::double / nullif(billions, 0), 2) AS per_billion_tokens, round(2500.0::double / 2000, 4) AS of_budget FROM r""")
def hw_cost(spark, sf_dir):
    """Each user's events as the telemetry of one run."""
    return H.telemetry_costs(load(spark, sf_dir, "events"))


@query(f"SELECT round(150e9 / {_N}, 2) AS tokens_per_param, round(150e9 / {_N} / 20, 2) AS times_optimal FROM {_ARCH}")
def hw_overtraining(spark, sf_dir):
    a, b = H.overtraining()
    return spark.createDataFrame([(round(a, 2), round(b, 2))], "tokens_per_param double, times_optimal double")


@query("SELECT 4096::bigint AS seq, (18 * 2 * 8 * 128 * 4096 * 2)::bigint AS grouped, (18 * 2 * 16 * 128 * 4096 * 2)::bigint AS \"full\"")
def hw_kv_cache(spark, sf_dir):
    return H.kv_bytes(H.arch_frame(spark), 4096)


_HOURLY = "SELECT date_trunc('hour', ts) AS start, count(*) AS n, round(sum(value), 4) AS units FROM events WHERE event_type = 'value' OR value IS NOT NULL GROUP BY 1"


@query(_HOURLY)
def hw_throughput_hourly(spark, sf_dir):
    return H.throughput(load(spark, sf_dir, "events"))


@query("""SELECT event_id, user_id, round(value, 6) AS value, round(before, 6) AS before_mean FROM (
SELECT *, avg(value) OVER w AS before, count(value) OVER w AS k FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 5 PRECEDING AND 1 PRECEDING)) WHERE k = 5 AND value < 0.1 * before""")
def hw_slow_windows(spark, sf_dir):
    slow = H.slow_steps(load(spark, sf_dir, "events"), 5, 0.1, order=["ts", "event_id"], by=["user_id"])
    return slow.select("event_id", "user_id", F.round("value", 6).alias("value"), F.round("trailing", 6).alias("before_mean"))


@query("""WITH e AS (SELECT user_id, ts, event_id, epoch(ts) - lag(epoch(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS d FROM events WHERE event_type = 'error'),
r AS (SELECT *, sum(CASE WHEN d IS NULL OR d >= 86400 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS run FROM e)
SELECT user_id, min(ts) AS "begin", max(ts) AS "end", count(*) AS faults FROM r GROUP BY user_id, run""")
def hw_fault_sessions(spark, sf_dir):
    return H.fault_sessions(load(spark, sf_dir, "events"), "1 day")


@query("SELECT event_id, CASE WHEN event_id % 11 = 0 THEN 'missing_second' ELSE 'differs' END AS state FROM events WHERE event_id % 11 = 0 OR event_id % 97 = 1")
def hw_determinism_audit(spark, sf_dir):
    """Two runs, of which the second lost some steps and changed others."""
    one = load(spark, sf_dir, "events").select("event_id", "value", "event_type")
    two = one.where("event_id % 11 <> 0").withColumn("value", F.when(F.col("event_id") % 97 == 1, F.col("value") + 1).otherwise(F.col("value")))
    return H.determinism_audit(one, two, ["event_id"])


@query("SELECT round(42.95::double / 3.1, 2) AS speedup")
def hw_speedup(spark, sf_dir):
    one = spark.createDataFrame([(3.1, 42.95)], "before double, after double")
    return one.select(H.speedup(F.col("before"), F.col("after")).alias("speedup"))


@query("""SELECT event_type, n, round(n::double / sum(n) OVER (), 6) AS share FROM (SELECT event_type, count(*) AS n FROM events GROUP BY 1)""")
def hw_event_mix(spark, sf_dir):
    by = load(spark, sf_dir, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    return by.withColumn("share", F.round(F.col("n") / F.sum("n").over(Window.partitionBy(F.lit(0))), 6))
