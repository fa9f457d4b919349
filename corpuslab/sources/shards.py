"""Token shards: 16-bit sequences under the fingerprint of the tokenizer that packed them, and other sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.bpe import check_uint16, from_u16, require_fingerprint, to_u16


def write_shards(packed: DataFrame, path: str, fingerprint: str) -> None:
    """``packed(shard, seq, ids)`` as two bytes an id, in folders by fingerprint and shard. An id that 16 bits can't hold ends the write."""
    bad = F.exists("ids", lambda x: (x < 0) | (x >= 1 << 16))
    safe = packed.withColumn("ids", F.when(bad, F.raise_error(F.lit("id above 16 bits"))).otherwise(F.col("ids")))
    rows = safe.select("shard", "seq", F.size("ids").alias("n"), to_u16(F.col("ids")).alias("data"), F.lit(fingerprint).alias("fingerprint"))
    rows.write.partitionBy("fingerprint", "shard").mode("overwrite").parquet(path)


def read_shards(spark: SparkSession, path: str, fingerprint: str) -> DataFrame:
    """``shard, seq, ids``; other tokenizers' folders are pruned, and a path without this one's ends the query."""
    rows = spark.read.parquet(path)
    here = rows.where(F.col("fingerprint") == fingerprint)
    if not here.limit(1).count():
        require_fingerprint(rows.limit(1), fingerprint).collect()
    return here.select("shard", "seq", from_u16(F.col("data")).alias("ids"))


def write_examples(sft: DataFrame, path: str, per_file: int = 50_000) -> None:
    """Instruction examples as JSON lines, by condition, in files of bounded length."""
    sft.write.partitionBy("condition").option("maxRecordsPerFile", per_file).mode("overwrite").json(path)


__all__ = ["check_uint16", "read_shards", "write_examples", "write_shards"]
