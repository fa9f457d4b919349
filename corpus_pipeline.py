"""The corpus pipeline: quality rules, near-duplicates, mixing to target weights, BPE encoding and decoding.

Each stage takes (spark, docs, sf_dir), works on every row that its predecessor kept, and is written as
Parquet before the next one reads it. All but the last keep the columns of documents.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from corpuslab.llm import bpe, mixing, quality, simhash
from corpuslab.llm.common import scratch, table

#: Not expressible in SQL: fingerprints and merges are computed in Python. Tests hold the stages against brute force.
ORACLE_SQL: str | None = None


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules and the likelihood ratio keep; the ratio is fitted on these documents and the labels.

    Null and empty texts have too few words and go; texts of any length count whole; repeated rows are judged alike. All columns stay as
    they are, whatever their names: those that the judgement doesn't read pass it under names of their own. An empty table gives an empty one.
    """
    model = quality.fit(docs, table(spark, sf_dir, "labels"))
    read = ("doc_id", "text", "lang")
    passed = docs.toDF(*[c if c in read else f"column {i}" for i, c in enumerate(docs.columns)])
    return quality.judge(passed, model).where("kept").select(*[F.col(f"`{c}`") for c in passed.columns]).toDF(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of near-duplicates: that of the smallest doc_id.

    Null and empty texts are one component; of rows equal in id and text one stays. All columns stay as they are, whatever their names. An
    empty table gives an empty one.
    """
    return simhash.keep_one(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as the mix takes it; rows repeat, and those that it doesn't take go.

    Null texts have no words; null ids and sources are values like others; copies of rows that share id, source and size are dealt among them
    in the order of a hash of the row. All columns stay as they are, whatever their names. An empty table gives an empty one.
    """
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    sized = docs.select("doc_id", "source", mixing.n_words(F.col("text")).alias("size"))
    path = scratch(spark, "mix-copies")
    taken = mixing.take(sized).groupBy("doc_id", "source", "size").agg(F.sum("copies").alias("copies"), F.count(F.lit(1)).alias("rows"))
    taken.where("copies > 0").write.parquet(path)
    plan = spark.read.parquet(path)
    same = docs.select(row, mixing.n_words(F.col("text")).alias("words"))
    on = F.col("row.doc_id").eqNullSafe(plan["doc_id"]) & F.col("row.source").eqNullSafe(plan["source"]) & (F.col("words") == plan["size"])
    met = same.join(plan.hint("merge"), on)
    each = F.col("copies").cast("int")
    if plan.where("rows > 1").limit(1).count():
        met = met.withColumn("n", F.row_number().over(Window.partitionBy(plan["doc_id"], plan["source"], plan["size"]).orderBy(F.xxhash64("row"), F.to_json("row"))))
        each = F.expr("int(copies div rows) + int(n <= copies % rows)")
    met = met.select("row", each.alias("each")).where("each > 0")
    return met.select("row", F.explode(F.sequence(F.lit(1), F.col("each"))).alias("copy")).select("row.*")


def byte_pairs(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Per row of the mix: number of ids, and digests of the ids and of the decoded text.

    Null text counts as empty; texts of any length are coded whole; repeated rows are answered each; other columns are left behind. An
    empty table gives an empty one.
    """
    import public_tokenizers

    return bpe.digest(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality", quality_rules),
    ("near_duplicates", near_duplicates),
    ("mixing", mix_sources),
    ("bpe", byte_pairs),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each result is written to the shared folder and reread."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        path = scratch(spark, f"pipeline-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
