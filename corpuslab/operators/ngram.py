"""Count-based n-gram models: counts, smoothing, scoring at needed positions, and loss measures."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.arrays import grams, hashed_grams, once
from ..tables import cleaned

START, END = "<s>", "</s>"


def tokens(text: Column) -> Column:
    """Lower-case words."""
    return F.regexp_extract_all(F.lower(text), F.lit(r"\S+"), F.lit(0))


def spans(df: DataFrame, order: int, keys: list[str], text: str = "text") -> DataFrame:
    """``keys``, ``pos``, ``context`` (the order-1 words before, joined) and ``token``: one row for each position."""
    df = once(df, *keys, _t=F.concat(F.array_repeat(F.lit(START), order - 1), tokens(F.col(text))))
    padded = F.col("_t")
    last = F.slice(padded, F.lit(order), F.greatest(F.size(padded) - (order - 1), F.lit(0)))
    if order == 1:
        return df.select(*keys, F.posexplode(last).alias("pos", "token")).select(*keys, "pos", F.lit("").alias("context"), "token")
    before = F.slice(grams(padded, order - 1), F.lit(1), F.greatest(F.size(padded) - (order - 1), F.lit(0)))
    pairs = F.zip_with(before, last, lambda c, t: F.struct(c.alias("context"), t.alias("token")))
    return df.select(*keys, F.posexplode(pairs).alias("pos", "p")).select(*keys, "pos", "p.context", "p.token")


def train(df: DataFrame, order: int, by: list[str] | None = None, text: str = "text") -> DataFrame:
    """``context``, ``token`` and ``cnt`` (by group); counted inside tasks first, one shuffle."""
    return spans(df, order, by or [], text).groupBy(*(by or []), "context", "token").agg(F.count(F.lit(1)).alias("cnt"))


class AddK:
    """(c(h, w) + k) / (c(h) + k (V + 1)) over one table of counts; with ``by``, a model for each of that column's values, all in one plan."""

    def __init__(self, counts: DataFrame, k: float = 1.0, by: str | None = None):
        self.counts, self.k, self.keys = counts, k, [by] if by else []
        self.contexts = counts.groupBy(*self.keys, "context").agg(F.sum("cnt").alias("ch"))
        if by:  # a row for each value
            self.vocabulary = counts.select(by, "token").distinct().groupBy(by).agg(F.count(F.lit(1)).alias("_v"))
        else:
            self.vocabulary = counts.select("token").distinct().count()

    def probs(self, needed: DataFrame) -> DataFrame:
        """``needed`` with ``logp``. Only needed pairs are looked up: counts are semi-joined with them before the join. A value of ``by`` without counts has no probability."""
        pair, head = [*self.keys, "context", "token"], [*self.keys, "context"]
        pairs = needed.select(*pair).distinct()
        here = self.counts.join(pairs, pair, "left_semi")
        heads = self.contexts.join(pairs.select(*head).distinct(), head, "left_semi")
        told = needed.join(here.select(*pair, "cnt"), pair, "left").join(heads, head, "left")
        told = told.join(self.vocabulary, self.keys, "left") if self.keys else told.withColumn("_v", F.lit(self.vocabulary))
        p = (F.coalesce("cnt", F.lit(0)) + self.k) / (F.coalesce("ch", F.lit(0)) + self.k * (F.col("_v") + 1))
        return told.withColumn("logp", F.log(p)).drop("cnt", "ch", "_v")


class Interpolated:
    """weight * c(h, w) / c(h) + (1 - weight) * lower(w); the weight is 0 where the context was never seen."""

    def __init__(self, counts: DataFrame, lower: AddK, weight: float = 0.7):
        self.counts, self.lower, self.weight = counts, lower, weight
        self.contexts = counts.groupBy("context").agg(F.sum("cnt").alias("ch"))

    def probs(self, needed: DataFrame) -> DataFrame:
        lower = self.lower.probs(needed.select(F.lit("").alias("context"), "token").distinct()).select("token", F.exp("logp").alias("p0"))
        told = needed.join(self.counts.select("context", "token", "cnt"), ["context", "token"], "left").join(self.contexts, "context", "left").join(lower, "token")
        weight = F.when(F.col("ch").isNull(), 0.0).otherwise(self.weight)
        p = weight * F.coalesce(F.col("cnt") / F.col("ch"), F.lit(0.0)) + (1 - weight) * F.col("p0")
        return told.withColumn("logp", F.log(p)).drop("cnt", "ch", "p0")


class KneserNey:
    """Bigram model of absolute discounting whose lower order counts contexts, not occurrences; ``continuation`` false gives plain absolute discounting."""

    def __init__(self, counts: DataFrame, discount: float = 0.75, continuation: bool = True):
        self.counts, self.d = counts, discount
        self.contexts = counts.groupBy("context").agg(F.sum("cnt").alias("ch"), F.count(F.lit(1)).alias("types"))
        self.lower = counts.groupBy("token").agg((F.count(F.lit(1)) if continuation else F.sum("cnt")).alias("n"))
        self.total, self.vocabulary = self.lower.agg(F.sum("n"), F.count(F.lit(1))).first()

    def probs(self, needed: DataFrame) -> DataFrame:
        told = needed.join(self.counts.select("context", "token", "cnt"), ["context", "token"], "left").join(self.contexts, "context", "left").join(self.lower, "token", "left")
        below = (F.coalesce("n", F.lit(0)) + 1) / F.lit(float((self.total or 0) + (self.vocabulary or 0) + 1))
        seen = F.greatest(F.coalesce("cnt", F.lit(0)) - self.d, F.lit(0.0)) / F.col("ch")
        p = F.when(F.col("ch").isNull(), below).otherwise(seen + self.d * F.col("types") / F.col("ch") * below)
        return told.withColumn("logp", F.log(p)).drop("cnt", "ch", "types", "n")


def score(df: DataFrame, model, order: int, keys: list[str], text: str = "text") -> DataFrame:
    """Sum of log probabilities and number of tokens for each key."""
    scored = model.probs(spans(df, order, keys, text))
    return scored.groupBy(*keys).agg(F.sum("logp").alias("ll"), F.count(F.lit(1)).alias("n_tokens"))


def score_groups(df: DataFrame, model, order: int, by: list[str], text: str = "text") -> DataFrame:
    """``score`` of whole groups. Occurrences are counted first, so the model is asked once for each group's distinct n-gram and a frequent context is no hot key of occurrences."""
    asked = train(df, order, by, text).withColumnRenamed("cnt", "times")
    return model.probs(asked).groupBy(*by).agg(F.sum(F.col("times") * F.col("logp")).alias("ll"), F.sum("times").alias("n_tokens"))


def split_loss(df: DataFrame, order: int, k: float, by: str, text: str = "text", slices: int = 2) -> dict:
    """Log probability of the ``held_out`` rows of each value of ``by`` under an add-``k`` model of the others' contexts of that value, with one vocabulary.

    The sum of log (c(h, w) + k) - log (c(h) + k (V + 1)) falls into a sum over distinct n-grams and one over distinct contexts, so nothing is
    joined: one aggregation for each holds both sides' counts. N-grams run in ``slices`` parts of their keys (64-bit numbers), contexts in half as many, one after
    the other, so that disk holds the keys of one part alone. Only sums by ``by`` come to the driver. ``order`` is 2 at least.
    """
    words = once(df, by, "held_out", _t=F.concat(F.array_repeat(F.lit(START), order - 1), tokens(F.col(text))))
    seen = words.where("not held_out").select(F.explode(F.array_distinct(F.slice("_t", order, F.greatest(F.size("_t"), F.lit(1))))).alias("w"))
    with cleaned(df.sparkSession):
        vocabulary = seen.distinct().count()
        out: dict = {}
        for width, add, sign, parts in ((order, k, 1.0, slices), (order - 1, k * (vocabulary + 1), -1.0, max(1, slices // 2))):
            first = F.slice(hashed_grams(F.col("_t"), width), F.lit(1), F.greatest(F.size("_t") - (order - 1), F.lit(0)))
            for part in range(parts):
                keys = once(words, by, "held_out", _g=F.filter(first, lambda x: F.pmod(x, F.lit(parts)) == part))  # noqa: B023
                keys = keys.select(by, "held_out", F.explode("_g").alias("g"))
                counts = keys.groupBy(by, "g").agg(F.count_if(~F.col("held_out")).alias("n"), F.count_if("held_out").alias("times")).where("times > 0")
                for value, ll in counts.groupBy(by).agg(F.sum(F.col("times") * F.log(F.col("n") + F.lit(add)))).collect():
                    out[value] = out.get(value, 0.0) + sign * ll
    return out


def bits_per_byte(nll: Column, n_bytes: Column) -> Column:
    return nll / (F.lit(math.log(2)) * n_bytes)


def loss_report(scored: DataFrame, by: list[str]) -> DataFrame:
    """Loss of ``scored(ll, n_tokens, n_chars, n_bytes, n_words)`` by byte, character, token and word, and perplexity."""
    s = {c: F.sum(c) for c in ("ll", "n_tokens", "n_chars", "n_bytes", "n_words")}
    return scored.groupBy(*by).agg(
        F.round(bits_per_byte(-s["ll"], s["n_bytes"]), 6).alias("bits_per_byte"),
        F.round(-s["ll"] / math.log(2) / s["n_chars"], 6).alias("bits_per_char"),
        F.round(-s["ll"] / s["n_tokens"], 6).alias("nats_per_token"),
        F.round(-s["ll"] / s["n_words"], 6).alias("nats_per_word"),
        F.round(F.exp(-s["ll"] / s["n_tokens"]), 2).alias("perplexity"),
    )


def tokenizer_invariance(scored: DataFrame, by: list[str], units: dict[str, Column]) -> DataFrame:
    """One model's loss over ``scored(ll, n_bytes, ...)`` under several ways to count tokens: nats for each unit follow the unit, bits per byte don't move."""
    sums = scored.groupBy(*by).agg(F.sum("ll").alias("ll"), F.sum("n_bytes").alias("_b"), *[F.sum(c).alias(u) for u, c in units.items()])
    rows = sums.unpivot([*by, "ll", "_b"], list(units), "unit", "n_units")
    return rows.select(*by, "unit", "n_units", F.round(-F.col("ll") / F.col("n_units"), 6).alias("nats_per_unit"), F.round(bits_per_byte(-F.col("ll"), F.col("_b")), 6).alias("bits_per_byte"))


def assert_same_script(report: DataFrame, script: str = "script") -> DataFrame:
    """The report; ends the query if it would rank bits per byte across scripts."""
    several = report.agg(F.countDistinct(script).alias("_k"))
    return report.crossJoin(F.broadcast(several)).withColumn(script, F.when(F.col("_k") > 1, F.raise_error(F.lit("bits per byte can't be ranked across scripts"))).otherwise(F.col(script))).drop("_k")
