"""The queries of this subpackage, with production parameters over whole tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .common import table


def _vocab(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_ogg_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import ogg

    return ogg.digest(table(spark, sf_dir, "documents"))


def op2_feistel_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import sharding

    return sharding.shard_documents(table(spark, sf_dir, "documents"))


def op3_simhash_anchors(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import simhash

    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op4_bloom_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import lmscore

    return lmscore.score(table(spark, sf_dir, "documents"))


def op5_llr_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import quality

    docs = table(spark, sf_dir, "documents")
    judged = quality.judge(docs.select("doc_id", "text", "lang"), quality.fit(docs, table(spark, sf_dir, "labels")))
    return judged.drop("text", "lang")


def op6_knapsack_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import mixing

    return mixing.mix_sizes(table(spark, sf_dir, "documents"))


def op7_range_coded_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import tokenfiles

    return tokenfiles.digest(table(spark, sf_dir, "documents"), _vocab("word_bpe_49k.json"))


def op8_html_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import htmltext

    pages = table(spark, sf_dir, "pages")
    return htmltext.main_text(pages, htmltext.learn(pages))


def op9_bloom_cascade(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import urlfilter

    return urlfilter.judge(table(spark, sf_dir, "pages"), urlfilter.block_list(spark))


def op10_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import bpe

    return bpe.digest(table(spark, sf_dir, "documents"), _vocab("byte_bpe_50k.json"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_ogg_media, op2_feistel_shards, op3_simhash_anchors, op4_bloom_lm, op5_llr_quality, op6_knapsack_mix, op7_range_coded_ids, op8_html_region, op9_bloom_cascade, op10_byte_bpe)}


def oracle_sql() -> dict[str, str]:
    from . import urlfilter

    return {"op9_bloom_cascade": urlfilter.SQL}
