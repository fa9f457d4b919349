"""The given tables with their declared schemas."""

from __future__ import annotations

import contextlib
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int",
    "benchmark": "item_id long, text string",
    "conversations": "conv_id long, turn long, role string, text string",
    "pages": "page_id long, url string, html string",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "region": "r_regionkey int, r_name string",
}


def load(spark: SparkSession, sf_dir: str, name: str, *, event_time: bool = False) -> DataFrame:
    """A table by its declared schema, pruned by whatever is selected. ``event_time`` casts the events' clock to a zoned timestamp, which watermarks need."""
    df = spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")
    return df.withColumn("ts", F.col("ts").cast("timestamp")) if event_time else df


def check_schema(spark: SparkSession, sf_dir: str, name: str) -> list[str]:
    """Declared columns that the files lack."""
    there = set(spark.read.parquet(f"{sf_dir}/{name}.parquet").columns)
    return [c.split()[0] for c in SCHEMAS[name].split(", ") if c.split()[0] not in there]


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: the session's ``spark.checkpoint.dir``, which is made the context's where it has none.

    Only on one machine, where the session names none, is a local folder set; a cluster without one ends the query.
    """
    context = spark.sparkContext
    base = spark.conf.get("spark.checkpoint.dir", None)
    current = context._jsc.sc().getCheckpointDir()
    if not base and current.isEmpty() and not context.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir names no folder")
    if current.isEmpty():
        context.setCheckpointDir(base or "/tmp/corpuslab-checkpoints")
        current = context._jsc.sc().getCheckpointDir()
    return base or current.get()


@contextlib.contextmanager
def cleaned(spark: SparkSession) -> Iterator[None]:
    """Spark drops each query's shuffle files at its end, not when the driver happens to collect garbage."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.set(key, before) if before is not None else spark.conf.unset(key)
