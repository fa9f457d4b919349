"""Joins that Spark SQL lacks, without cross products: as-of, range by bands, intervals, and salting of hot keys."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: list[str], at: str, values: list[str], *, tie: str) -> DataFrame:
    """Each left row with the values of the latest right row of its key at or before its time.

    Both sides are put in one order per key and the last right value is carried on: one shuffle, no product. ``tie`` orders right rows of one time.
    """
    a = left.select("*", F.lit(1).alias("_side"), F.lit(None).cast(right.schema[tie].dataType).alias("_tie"), F.lit(None).cast(right.select(F.struct(*values)).schema[0].dataType).alias("_v"))
    b = right.select(*by, at, F.lit(0).alias("_side"), F.col(tie).alias("_tie"), F.struct(*values).alias("_v"))
    order = Window.partitionBy(*by).orderBy(at, "_side", "_tie").rowsBetween(Window.unboundedPreceding, 0)
    told = a.unionByName(b, allowMissingColumns=True).withColumn("_last", F.last("_v", ignorenulls=True).over(order))
    return told.where("_side = 1").select(*left.columns, *[F.col(f"_last.{v}").alias(f"asof_{v}") for v in values])


def band_join(left: DataFrame, right: DataFrame, value: Column, low: Column, high: Column, width: float) -> DataFrame:
    """Left rows whose ``value`` lies in [low, high) of a right row: an equi-join on bands of ``width``, then the exact test. Right rows are copied to each band that they touch."""
    a = left.withColumn("_band", F.floor(value / width))
    b = right.withColumn("_band", F.explode(F.sequence(F.floor(low / width), F.floor(high / width))))
    return a.join(b, "_band").where((value >= low) & (value < high)).drop("_band")


def interval_join(left: DataFrame, right: DataFrame, by: list[str], at: str, other: str, seconds: int) -> DataFrame:
    """Pairs of one key whose right time is within ``seconds`` after the left one; buckets of that length make it an equi-join on two buckets."""
    epoch = lambda c: F.unix_micros(F.col(c).cast("timestamp")) / 1e6
    a = left.withColumn("_w", F.explode(F.array(F.floor(epoch(at) / seconds), F.floor(epoch(at) / seconds) + 1)))
    b = right.withColumn("_w", F.floor(epoch(other) / seconds))
    return a.join(b, [*by, "_w"]).where((epoch(other) > epoch(at)) & (epoch(other) <= epoch(at) + seconds)).drop("_w")


def salted_join(left: DataFrame, right: DataFrame, on: list[str], salts: int = 16, how: str = "inner") -> DataFrame:
    """A join whose hot left keys spread over ``salts`` tasks; the right side is copied to each. Inner and left joins alone."""
    if how not in ("inner", "left"):
        raise ValueError("salting copies the right side, so its rows can't be kept alone")
    a = left.withColumn("_salt", F.pmod(F.xxhash64(*[F.col(f"`{c}`") for c in left.columns]), F.lit(salts)).cast("int"))
    b = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [*on, "_salt"], how).drop("_salt")


def two_level_sum(df: DataFrame, by: list[str], value: Column, name: str, salts: int = 16) -> DataFrame:
    """A sum by key in two steps, for keys whose map-side partial sums are many."""
    first = df.withColumn("_salt", F.pmod(F.xxhash64(*[F.col(f"`{c}`") for c in df.columns]), F.lit(salts))).groupBy(*by, "_salt").agg(F.sum(value).alias(name))
    return first.groupBy(*by).agg(F.sum(name).alias(name))
