"""Mixing sources to target weights by exact subset-sum budget fitting.

Targets are water-filled: a source gets its weight's share of all words, at most ``MOST`` times its own,
and what is above is shared again by weight. A source takes every document as often as its target
holds its size; what then remains of the budget is fitted by token length: documents are counted by
exact length, the same share of every length is taken, and a bounded-knapsack dynamic programme over
the counts left settles the last words. Within a length, seeded hashes say which documents are meant.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import scratch, store

MOST = 3
#: Sources whose rows come to the driver at most.
MOST_SOURCES = 100_000
WEIGHTS = (1.0, 2.0, 3.0)
SEED = 11
#: Buckets that a length's documents are ranked in, so that one length may hold a third of all rows.
BUCKETS = 256
#: Words that the dynamic programme settles at most; the share taken before leaves less than this, or greedy steps do.
WINDOW = 1 << 17


def n_words(text: Column) -> Column:
    """Words of a text; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def water_fill(sizes: list[int], weights: list[float], most: float = MOST) -> list[float]:
    """Targets that share all sizes by weight, none above ``most`` times its size."""
    out, left, rest = [0.0] * len(sizes), float(sum(sizes)), [i for i, n in enumerate(sizes) if n > 0]
    while rest:
        unit = left / sum(weights[i] for i in rest)
        full = [i for i in rest if weights[i] * unit > most * sizes[i]]
        if not full:
            for i in rest:
                out[i] = weights[i] * unit
            break
        for i in full:
            out[i] = float(most * sizes[i])
            left -= out[i]
        rest = [i for i in rest if i not in set(full)]
    return out


def fit_counts(lengths: np.ndarray, counts: np.ndarray, budget: int) -> np.ndarray:
    """How many documents of each length to take, so that their words come as near ``budget`` from below as can be found.

    The same share of every length first, then the longest that still fit until less than WINDOW is
    left, then a bounded knapsack over the counts left: bit k of a state says that k words can be had.
    """
    taken = np.zeros(len(lengths), np.int64)
    total = int((lengths * counts).sum())
    if budget <= 0 or not total:
        return taken
    if budget >= total:
        return counts.astype(np.int64)
    taken = np.minimum(counts, np.floor(counts * (budget / total)).astype(np.int64))
    left = budget - int((lengths * taken).sum())
    order = np.argsort(-lengths)
    for i in order:
        if left < WINDOW:
            break
        more = min(int(counts[i] - taken[i]), (left - WINDOW + int(lengths[i])) // int(lengths[i]), left // int(lengths[i]))
        if more > 0:
            taken[i] += more
            left -= more * int(lengths[i])
    spare = [(int(lengths[i]), i, int(counts[i] - taken[i])) for i in order[::-1] if 0 < lengths[i] <= left and counts[i] > taken[i]]
    mask, reach, steps = (1 << (left + 1)) - 1, 1, []
    for length, i, n in spare:
        n, k = min(n, left // length), 1
        while n > 0:  # counts as sums of powers of two
            k = min(k, n)
            steps.append((length * k, i, k, reach))
            reach |= (reach << length * k) & mask
            n, k = n - k, 2 * k
        if reach >> left & 1:
            break
    at = reach.bit_length() - 1
    for size, i, k, before in reversed(steps):
        if not before >> at & 1:
            taken[i] += k
            at -= size
    return taken


def plan_targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, most: float = MOST, *, bound: int = MOST_SOURCES) -> DataFrame:
    """``source``, ``source_size``, ``target``: one row for each source, by code point, null last, weights repeating.

    ``sizes`` has one row for each source; up to ``bound`` these rows come to the driver, more are filled by sorted running sums in the cluster.
    """
    if sizes.count() > bound:
        return _spread_targets(sizes, weights, most)
    rows = sorted(((r[0], r[1]) for r in sizes.select("source", "source_size").collect()), key=lambda r: (r[0] is None, [ord(c) for c in r[0] or ""]))
    targets = water_fill([r[1] for r in rows], [weights[i % len(weights)] for i in range(len(rows))], most)
    return sizes.sparkSession.createDataFrame([(a, b, t) for (a, b), t in zip(rows, targets)], "source string, source_size long, target double")


def _spread_targets(sizes: DataFrame, weights: tuple[float, ...], most: float) -> DataFrame:
    """The targets by one pass over the sources sorted by size for their weight: those below the level that all above it share are full."""
    whole = Window.partitionBy(F.lit(0))
    place = F.row_number().over(whole.orderBy(F.asc_nulls_last("source"))) - 1
    weight = F.element_at(F.array(*map(F.lit, weights)), F.pmod(place, F.lit(len(weights))).cast("int") + 1)
    told = sizes.select("source", "source_size", place.alias("place"), F.when(F.col("source_size") > 0, weight).otherwise(0.0).alias("w"), (most * F.col("source_size")).cast("double").alias("full"))
    before = whole.orderBy(F.try_divide("full", "w"), "place").rowsBetween(Window.unboundedPreceding, -1)
    given, shared = F.coalesce(F.sum("full").over(before), F.lit(0.0)), F.coalesce(F.sum("w").over(before), F.lit(0.0))
    told = told.withColumn("unit", F.try_divide(F.sum("source_size").over(whole) - given, F.sum("w").over(whole) - shared))
    level = F.max("unit").over(whole)  # it rises while full sources are set aside, and falls once others are
    return told.select("source", "source_size", F.when(F.col("w") == 0, 0.0).otherwise(F.least("full", F.col("w") * F.coalesce(level, F.lit(0.0)))).alias("target"))


def take(docs: DataFrame, *, weights: tuple[float, ...] = WEIGHTS, most: int = MOST, seed: int = SEED) -> DataFrame:
    """``docs(doc_id, source, size, ...)`` with ``source_size``, ``target`` and ``copies``, how often the mix holds each row.

    Columns of ``docs`` with the names of the three are replaced, all others stay. Rows equal in doc_id, source and size are told apart by
    rank only; null ids and sources are values like others. Documents without words are taken as often as their source's whole documents
    are. ``docs`` is read twice. An empty table gives an empty one.
    """
    spark = docs.sparkSession
    docs = docs.drop("source_size", "target", "copies")
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    h = F.xxhash64("doc_id", F.lit(seed))
    docs = docs.select(row, "doc_id", "source", "size", h.alias("h"), F.pmod(h, F.lit(BUCKETS)).cast("int").alias("b"))
    counts = store(docs.groupBy("source", "size", "b").agg(F.count(F.lit(1)).alias("n")), scratch(spark, "mix-lengths"))
    targets = plan_targets(counts.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).cast("long").alias("source_size")), weights, most)
    by_length = counts.groupBy("source", "size").agg(F.sum("n").alias("n"))
    joined = by_length.join(targets, by_length["source"].eqNullSafe(targets["source"])).drop(targets["source"])

    def fit(rows: pd.DataFrame) -> pd.DataFrame:
        target, size = rows["target"].iloc[0], rows["source_size"].iloc[0]
        whole = int(target // size) if size else 0
        some = fit_counts(rows["size"].to_numpy(), rows["n"].to_numpy(), int(round(target - whole * size)) if whole < most else 0)
        return rows.assign(whole=whole, some=some)[["source", "size", "source_size", "target", "whole", "some"]]

    fitted = joined.groupBy("source").applyInPandas(fit, "source string, size long, source_size long, target double, whole int, some long")
    before = Window.partitionBy("source", "size").orderBy("b").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0))).drop("n")
    f, s = fitted.alias("f"), starts.alias("s")
    plan = s.join(f, F.col("s.source").eqNullSafe(F.col("f.source")) & (F.col("s.size") == F.col("f.size")))
    plan = plan.select(F.col("s.source").alias("its"), F.col("s.size").alias("length"), F.col("s.b").alias("part"), "before", "source_size", "target", "whole", "some")
    ranked = docs.withColumn("rank", F.row_number().over(Window.partitionBy("source", "size", "b").orderBy("h", "doc_id")))
    out = ranked.join(plan, F.col("source").eqNullSafe(F.col("its")) & (F.col("size") == F.col("length")) & (F.col("b") == F.col("part")))
    copies = F.col("whole") + (F.col("before") + F.col("rank") <= F.col("some")).cast("int")
    return out.select("row.*", "source_size", "target", copies.alias("copies"))


def mix_sizes(docs: DataFrame) -> DataFrame:
    """The mix of all documents: size in words, the source's size and target, and the words taken.

    Null texts have no words; long texts count whole; repeated rows are answered each; null ids and sources are values like others. An
    empty table gives an empty one; other columns are left behind, whatever their names.
    """
    taken = take(docs.select("doc_id", "source", n_words(F.col("text")).alias("size")))
    return taken.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).cast("long").alias("taken"))
