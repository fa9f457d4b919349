"""SQL names of the measures, for sessions that speak SQL."""

from __future__ import annotations

from pyspark.sql import SparkSession

FUNCTIONS = {
    "bits_per_byte(nll DOUBLE, n_bytes BIGINT) RETURNS DOUBLE": "nll / (ln(2) * n_bytes)",
    "z_over_chance(acc DOUBLE, n BIGINT, k INT) RETURNS DOUBLE": "(acc - 1D / k) / sqrt(acc * (1 - acc) / n)",
    "wilson_low(k BIGINT, n BIGINT) RETURNS DOUBLE": "greatest(0D, ((k / n + 1.9208D / n) - 1.96D * sqrt((k / n) * (1 - k / n) / n + 0.9604D / (n * n))) / (1 + 3.8416D / n))",
    "wilson_high(k BIGINT, n BIGINT) RETURNS DOUBLE": "least(1D, ((k / n + 1.9208D / n) + 1.96D * sqrt((k / n) * (1 - k / n) / n + 0.9604D / (n * n))) / (1 + 3.8416D / n))",
    "md5_bucket(key STRING) RETURNS BIGINT": "cast(conv(substr(md5(key), 1, 8), 16, 10) AS BIGINT)",
}


def register_all(spark: SparkSession) -> None:
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
