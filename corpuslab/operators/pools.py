"""Pools: sizes, unique sizes, duplication, mixture plans, ceilings, hold-out."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.pretokenize import n_words
from ..functions.views import bucket


def sizes() -> list[Column]:
    text = F.col("text")
    return [
        F.count(F.lit(1)).alias("docs"),
        F.sum(F.length(text)).cast("long").alias("chars"),
        F.sum(F.octet_length(text)).cast("long").alias("bytes"),
        F.sum(n_words(text)).cast("long").alias("words"),
    ]


def pool_table(docs: DataFrame, by: tuple[str, ...] = ("lang", "source")) -> DataFrame:
    """Documents, characters, bytes and words of each pool; partial sums, one shuffle."""
    return docs.groupBy(*by).agg(*sizes())


def pool_rollup(docs: DataFrame) -> DataFrame:
    """The same with totals by language and over all; ``level`` is the grouping id."""
    return docs.rollup("lang", "source").agg(F.grouping_id().cast("int").alias("level"), *sizes())


def unique_documents(docs: DataFrame) -> DataFrame:
    """The first document (lowest id) of each distinct text. Digests are shuffled, never texts, until ids are known."""
    first = docs.select("doc_id", F.md5("text").alias("d")).groupBy("d").agg(F.min("doc_id").alias("doc_id"))
    return docs.join(first.select("doc_id"), "doc_id", "left_semi")


def unique_pool(docs: DataFrame, by: tuple[str, ...] = ("lang",)) -> DataFrame:
    """Pool sizes without exact copies, each text credited to its first document; sizes travel with the digest, so that texts are read once."""
    text = F.col("text")
    told = docs.select(F.md5(text).alias("d"), "doc_id", *by, F.length(text).alias("c"), n_words(text).alias("w"))
    first = told.groupBy("d").agg(F.min_by(F.struct(*by, "c", "w"), "doc_id").alias("s"))
    return first.groupBy(*[F.col(f"s.{b}").alias(b) for b in by]).agg(F.count(F.lit(1)).alias("docs"), F.sum("s.c").cast("long").alias("chars"), F.sum("s.w").cast("long").alias("words"))


def duplication_report(docs: DataFrame) -> DataFrame:
    """By language: documents, distinct texts, lines, distinct lines of a document that recur in it."""
    lines = F.filter(F.split("text", "\n"), lambda x: F.length(x) > 0)
    told = docs.select("lang", F.md5("text").alias("d"), F.size(lines).alias("n"), F.size(F.array_distinct(lines)).alias("u"))
    return told.groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.countDistinct("d").alias("texts"), F.sum("n").cast("long").alias("lines"), F.sum(F.col("n") - F.col("u")).cast("long").alias("repeated_lines"))


def solve_weights(pools: DataFrame, policy: str, *, alpha: float = 0.5, shares: dict[str, float] | None = None, total: float | None = None, max_epochs: float | None = None, key: str = "pool", size: str = "tokens") -> DataFrame:
    """``pools`` with ``weight``: ``proportional``, ``temperature`` (size^alpha), ``fixed`` (given shares), or ``capped``.

    ``capped`` starts from size^alpha and clips pools at ``max_epochs`` times their size of the ``total``, sharing what is above over the others
    until none is above; the sorted running form finds the same in one pass over the pools.
    """
    whole = Window.partitionBy(F.lit(0))
    if policy == "fixed":
        table = F.create_map(*[F.lit(x) for kv in (shares or {}).items() for x in kv])
        raw = F.coalesce(F.element_at(table, F.col(key)), F.lit(0.0))
    elif policy == "proportional":
        raw = F.col(size).cast("double")
    else:
        raw = F.pow(F.col(size).cast("double"), alpha)
    weighted = pools.withColumn("_raw", raw).withColumn("weight", F.col("_raw") / F.sum("_raw").over(whole))
    if policy != "capped":
        return weighted.drop("_raw")
    cap = F.lit(float(max_epochs)) * F.col(size) / F.lit(float(total))
    order = Window.partitionBy(F.lit(0)).orderBy(F.col("_cap") / F.col("_raw"), key)
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    told = weighted.withColumn("_cap", cap).withColumn("_done", F.coalesce(F.sum("_cap").over(before), F.lit(0.0)))
    told = told.withColumn("_left", F.sum("_raw").over(whole) - F.coalesce(F.sum("_raw").over(before), F.lit(0.0)))
    # a pool is clipped if, with all tighter ones clipped, its share of the rest is still above its cap
    told = told.withColumn("_unit", (1 - F.col("_done")) / F.col("_left")).withColumn("_clip", F.col("_raw") * F.col("_unit") > F.col("_cap"))
    unit = F.min(F.when(~F.col("_clip"), F.struct(F.col("_cap") / F.col("_raw"), F.col("_unit").alias("u")))).over(whole)["u"]
    feasible = F.sum("_cap").over(whole) >= 1 - 1e-12
    told = told.withColumn("_u", unit).withColumn("_ok", feasible)
    weight = F.when(~F.col("_ok"), F.raise_error(F.lit("the pools can't fill the budget at this cap")).cast("double")).when(F.col("_clip"), F.col("_cap")).otherwise(F.col("_raw") * F.col("_u"))
    return told.withColumn("weight", weight).drop("_raw", "_cap", "_done", "_left", "_unit", "_clip", "_u", "_ok")


def mixture_plan(weighted: DataFrame, total: float, size: str = "tokens") -> DataFrame:
    """Epochs of each pool at ``total`` tokens, and whether it is subsampled or repeated."""
    epochs = F.col("weight") * float(total) / F.col(size)
    kind = F.when(F.col("epochs") < 1, "subsampled").when(F.col("epochs") > 1, "repeated").otherwise("once")
    return weighted.withColumn("epochs", epochs).withColumn("kind", kind)


def sample_mixture(docs: DataFrame, plan: DataFrame, key: str, seed: str = "mix") -> DataFrame:
    """Every document floor(epochs) times, and once more for the md5 share that is left; ``epoch`` numbers the copies. No shuffle: the plan is a row for each pool."""
    pools = F.broadcast(plan.select(F.col(key).alias("_pool"), "epochs"))
    epochs = docs.join(pools, F.col(key).eqNullSafe(F.col("_pool"))).drop("_pool")  # documents without a pool are one, too
    more = (bucket(seed, F.col("doc_id")) < (F.col("epochs") - F.floor("epochs")) * F.lit(2.0**32)).cast("int")
    copies = epochs.withColumn("_n", (F.floor("epochs") + more).cast("int")).where("_n > 0")
    return copies.select("*", F.explode(F.sequence(F.lit(1), F.col("_n"))).alias("epoch")).drop("_n", "epochs")


def order_mixture(mixed: DataFrame, partitions: int, seed: str = "order") -> DataFrame:
    """Another order in each epoch: a range shuffle by digests."""
    at = F.md5(F.concat_ws("|", F.lit(seed), F.col("epoch").cast("string"), F.col("doc_id").cast("string")))
    return mixed.withColumn("_at", at).repartitionByRange(partitions, "epoch", "_at").sortWithinPartitions("epoch", "_at").drop("_at")


def data_ceiling(weighted: DataFrame, max_epochs: float, size: str = "tokens") -> DataFrame:
    """Most tokens that the mixture can train on before a pool is seen more than ``max_epochs`` times, and the pool that binds."""
    most = F.lit(float(max_epochs)) * F.col(size) / F.col("weight")
    return weighted.where("weight > 0").agg(F.min(most).alias("max_tokens"), F.min_by("pool", most).alias("binding"))


def ceiling_whatif(weighted: DataFrame, budgets: DataFrame, size: str = "tokens") -> DataFrame:
    """Epochs of every pool at every budget (two tiny relations)."""
    return weighted.crossJoin(F.broadcast(budgets)).withColumn("epochs", F.col("weight") * F.col("budget") / F.col(size))


def release_filter(docs: DataFrame, private: list[str]) -> DataFrame:
    """Documents of sources that may be passed on; null sources may not be known to be private and stay."""
    return docs.where(~F.coalesce(F.col("source").isin(private), F.lit(False)))


def split_holdout(docs: DataFrame, percent: int = 10, seed: str = "holdout") -> DataFrame:
    """``docs`` with ``held_out``, by a digest of the text: copies never straddle the split."""
    return docs.withColumn("held_out", bucket(seed, F.col("text")) % 100 < percent)
