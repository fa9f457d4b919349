"""Translation: aligned passages, script shares, target-script rate, fixture systems, and character n-gram F-scores with words."""

from __future__ import annotations

from collections import Counter

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import DoubleType

from ..functions.arrays import grams
from ..functions.views import abugida_view, bucket

LETTER, LATIN, TARGET = r"[\p{L}\p{M}]", r"\p{IsLatin}", r"\p{IsDevanagari}"
#: Shares of outputs in the target script that the fixture systems are built to have (the published ones, in percent).
SHARES = {("LRL->EN", "base"): 67, ("EN->LRL", "base"): 8, ("LRL->EN", "chat"): 81, ("EN->LRL", "chat"): 58}


def letters(text: Column) -> Column:
    return F.regexp_count(text, F.lit(LETTER)).cast("long")


def in_script(text: Column, script: str) -> Column:
    """Letters and marks of the script; an accent that stands alone counts for the letters of the other script."""
    return F.regexp_count(text, F.lit(f"[{script}&&{LETTER}]")).cast("long")


def script_share(text: Column) -> Column:
    n = letters(text)
    return F.struct(n.alias("letters"), in_script(text, LATIN).alias("latin"), in_script(text, TARGET).alias("marked"))


def is_target(text: Column, direction: Column, threshold: float = 0.5) -> Column:
    """More than ``threshold`` of the letters lie in the target script; an output without letters doesn't."""
    n = letters(text)
    of = F.when(direction == "EN->LRL", in_script(text, TARGET)).otherwise(in_script(text, LATIN))
    return F.coalesce((n > 0) & (of > threshold * n), F.lit(False))


def aligned_passages(bench: DataFrame) -> DataFrame:
    """Source and reference of both directions, one for each item; ``granularity`` tells that these are paragraphs."""
    one = bench.dropDuplicates(["item_id"])
    lrl, en = abugida_view(F.col("text")), F.lower("text")
    a = one.select("item_id", F.lit("EN->LRL").alias("direction"), en.alias("src"), lrl.alias("ref"))
    b = one.select("item_id", F.lit("LRL->EN").alias("direction"), lrl.alias("src"), en.alias("ref"))
    return a.unionByName(b).withColumn("granularity", F.lit("paragraph"))


def require_granularity(scores: DataFrame, wanted: str) -> DataFrame:
    """Ends the query where scores of another granularity would be set beside the wanted one."""
    wrong = F.col("granularity") != wanted
    return scores.withColumn("granularity", F.when(wrong, F.raise_error(F.lit("passages can't be compared with sentences"))).otherwise(F.col("granularity")))


def fixture_outputs(pairs: DataFrame, checkpoint: str) -> DataFrame:
    """Outputs of a fixture system: by md5 share the reference with every seventh word left out, else the source echoed. Not a measurement."""
    words = F.split("ref", " ")
    kept = F.array_join(F.filter(words, lambda w, i: i % 7 != 6), " ")
    share = F.when(F.col("direction") == "EN->LRL", SHARES["EN->LRL", checkpoint]).otherwise(SHARES["LRL->EN", checkpoint])
    good = bucket(f"mt-{checkpoint}", F.col("item_id"), F.col("direction")) % 100 < share
    prompting = "few_shot_completion" if checkpoint == "base" else "zero_shot_instruction"
    return pairs.select("*", F.lit(checkpoint).alias("checkpoint"), F.lit(prompting).alias("prompting"), F.when(good, kept).otherwise(F.col("src")).alias("hyp"))


def target_script_rate(outputs: DataFrame) -> DataFrame:
    hit = is_target(F.col("hyp"), F.col("direction")).cast("int")
    return outputs.groupBy("direction", "checkpoint", "prompting").agg(F.count(F.lit(1)).alias("n"), F.sum(hit).alias("in_script"), F.round(F.avg(hit), 6).alias("rate"))


def prompt_mt(pairs: DataFrame, kind: str, examples: str = "") -> DataFrame:
    """A completion prompt with examples, or a chat instruction: each checkpoint is asked in the form it was trained on."""
    if kind == "completion":
        return pairs.withColumn("prompt", F.concat(F.lit(examples), F.col("src"), F.lit(" =>")))
    return pairs.withColumn("prompt", F.concat(F.lit("<|user|>Translate "), F.col("direction"), F.lit(": "), F.col("src"), F.lit("\n<|assistant|>")))


PUNCT = r"[!-/:-@\[-`{-~]"


def chrf_words(text: Column) -> Column:
    """Words with punctuation at their edges split off."""
    spaced = F.regexp_replace(F.regexp_replace(text, rf"(^|\s)({PUNCT})(?=\S)", "$1$2 "), rf"(?<=\S)({PUNCT})(?=\s|$)", " $1")
    return F.filter(F.split(spaced, r"\s+"), lambda w: w != "")


def _marked(found: Column, order: str) -> Column:
    return F.transform(found, lambda g: F.struct(F.lit(order).alias("ord"), g.alias("g")))


def _gram_counts(df: DataFrame, keys: list[str], text: str, name: str, chars: int, words: int) -> DataFrame:
    bare = F.split(F.regexp_replace(text, r"\s+", ""), "")
    bare = F.filter(bare, lambda x: x != "")
    kinds = []
    for kind, units, top, glue in (("c", bare, chars, ""), ("w", chrf_words(F.col(text)), words, " ")):
        for n in range(1, top + 1):
            kinds.append(_marked(grams(units, n, glue), f"{kind}{n}"))
    return df.select(*keys, F.inline(F.concat(*kinds))).groupBy(*keys, "ord", "g").agg(F.count(F.lit(1)).alias(name))


def chrf_statistics(outputs: DataFrame, keys: list[str], chars: int = 6, words: int = 2) -> DataFrame:
    """Matched, hypothesis and reference n-grams by key and order; counts are joined, no UDF."""
    hyp, ref = _gram_counts(outputs, keys, "hyp", "h", chars, words), _gram_counts(outputs, keys, "ref", "r", chars, words)
    met = hyp.join(ref, [*keys, "ord", "g"], "full").select(*keys, "ord", F.coalesce("h", F.lit(0)).alias("h"), F.coalesce("r", F.lit(0)).alias("r"))
    return met.groupBy(*keys, "ord").agg(F.sum(F.least("h", "r")).alias("m"), F.sum("h").alias("h"), F.sum("r").alias("r"))


def chrf_from(statistics: DataFrame, by: list[str], beta: float = 2.0) -> DataFrame:
    """The score in percent: precision and recall are averaged over the orders that both sides have, then joined."""
    there = statistics.where("h > 0 and r > 0")
    told = there.groupBy(*by).agg(F.avg(F.col("m") / F.col("h")).alias("p"), F.avg(F.col("m") / F.col("r")).alias("q"))
    b = beta * beta
    return told.withColumn("chrf", F.when(F.col("p") + F.col("q") > 0, F.round(100 * (1 + b) * F.col("p") * F.col("q") / (b * F.col("p") + F.col("q")), 6)).otherwise(0.0)).drop("p", "q")


def chrf_sentence(outputs: DataFrame, keys: list[str], **options) -> DataFrame:
    return chrf_from(chrf_statistics(outputs, keys, **options), keys)


def chrf_corpus(outputs: DataFrame, keys: list[str], by: list[str], **options) -> DataFrame:
    """Counts are summed over the group before ratios are taken."""
    sums = chrf_statistics(outputs, keys, **options).groupBy(*by, "ord").agg(*[F.sum(c).alias(c) for c in ("m", "h", "r")])
    return chrf_from(sums, by)


@pandas_udf(DoubleType())
def chrf_row(hyp: pd.Series, ref: pd.Series) -> pd.Series:
    """The sentence score row by row, without a shuffle: for short outputs, and to check the other way."""
    import re

    def words(x: str) -> list[str]:
        x = re.sub(rf"(^|\s)({PUNCT})(?=\S)", r"\1\2 ", x)
        return re.sub(rf"(?<=\S)({PUNCT})(?=\s|$)", r" \1", x).split()

    def counts(x: str) -> list[Counter]:
        bare, w = "".join(x.split()), words(x)
        return [Counter(bare[i : i + n] for i in range(len(bare) - n + 1)) for n in range(1, 7)] + [Counter(" ".join(w[i : i + n]) for i in range(len(w) - n + 1)) for n in (1, 2)]

    def one(h: str | None, r: str | None) -> float:
        ratios = [(sum((a & b).values()), sum(a.values()), sum(b.values())) for a, b in zip(counts(h or ""), counts(r or ""))]
        ratios = [(m / a, m / b) for m, a, b in ratios if a and b]
        if not ratios:
            return 0.0
        p, q = (sum(x[i] for x in ratios) / len(ratios) for i in (0, 1))
        return 100 * 5 * p * q / (4 * p + q) if p + q else 0.0

    return pd.Series([one(h, r) for h, r in zip(hyp, ref)])


def split_quality(scored: DataFrame) -> DataFrame:
    """Mean score of all outputs, and of those in the right script alone: selection of language against quality."""
    hit = is_target(F.col("hyp"), F.col("direction"))
    return scored.groupBy("direction", "checkpoint").agg(F.round(F.avg("chrf"), 4).alias("all_outputs"), F.round(F.avg(F.when(hit, F.col("chrf"))), 4).alias("in_script"), F.round(F.avg(F.when(~hit, F.col("chrf"))), 4).alias("off_script"))


