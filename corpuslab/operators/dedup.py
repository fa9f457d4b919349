"""Near-duplicate classes by MinHash bands with exact verification, and connected components by star rounds."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from ..functions.arrays import grams
from ..tables import shared_folder


def shingles(text: Column, k: int = 5) -> Column:
    """Distinct hashes of k-word shingles, lower case; a shorter text is one shingle."""
    words = F.filter(F.split(F.lower(text), r"\s+"), lambda w: w != "")
    many = F.transform(grams(words, k), lambda g: F.xxhash64(g))
    return F.when(F.size(words) >= k, F.array_distinct(many)).otherwise(F.array(F.xxhash64(F.array_join(words, " "))))


def band_hashes(perms: int, bands: int):
    """A column function: one hash for each band of MinHashes of an array of shingle hashes."""

    @pandas_udf("array<bigint>")
    def of(column: pd.Series) -> pd.Series:
        rng = np.random.default_rng(7)
        a, b = (rng.integers(1, 1 << 63, perms, dtype=np.uint64) | np.uint64(1)), rng.integers(0, 1 << 63, perms, dtype=np.uint64)
        out = []
        with np.errstate(over="ignore"):
            for x in column:
                x = np.asarray(x, np.int64).view(np.uint64)
                least = np.full(perms, np.iinfo(np.uint64).max)
                for i in range(0, len(x), 4096):  # a long text in parts
                    z = x[i : i + 4096, None] * a + b
                    least = np.minimum(least, (z ^ (z >> np.uint64(29))).min(axis=0))
                mixed = least.reshape(bands, -1)
                h = np.zeros(bands, np.uint64)
                for k in range(mixed.shape[1]):
                    h = (h ^ mixed[:, k]) * np.uint64(0x9E3779B97F4A7C15)
                    h ^= h >> np.uint64(32)
                out.append(h.view(np.int64))
        return pd.Series(out)

    return of


def near_dup_clusters(docs: DataFrame, k: int = 5, perms: int = 64, bands: int = 16, threshold: float = 0.8, *, bucket_cap: int = 64) -> DataFrame:
    """``doc_id`` and ``cluster`` (the smallest id of the class) of every document.

    Equal texts are one node from the start. Candidates share a band of MinHashes, and are verified by Jaccard similarity. In a bucket of up to ``bucket_cap`` members
    all are compared; in larger ones each member is first compared with the least one and the next one by id. Of what is left there, every two members that these links
    haven't brought into one class are compared too, block by block of about ``bucket_cap`` members, so that no task holds a quadratic bucket.
    """
    shared_folder(docs.sparkSession)
    digests = docs.select("doc_id", F.md5("text").alias("d"), "text")
    nodes = digests.groupBy("d").agg(F.min("doc_id").alias("node"), F.first("text").alias("text"))
    sets = nodes.select("node", shingles(F.col("text"), k).alias("s"))
    banded = sets.select("node", F.posexplode(band_hashes(perms, bands)("s")).alias("band", "h"))
    w = Window.partitionBy("band", "h")
    told = banded.withColumns({"n": F.count(F.lit(1)).over(w), "first": F.min("node").over(w), "next": F.lead("node").over(w.orderBy("node"))}).where("n > 1").checkpoint()
    stars = told.select(F.col("first").alias("a"), F.col("node").alias("b")).union(told.select(F.col("node").alias("a"), F.col("next").alias("b")))
    small = told.where(F.col("n") <= bucket_cap).select("band", "h", "node")
    pairs = small.alias("x").join(small.alias("y"), ["band", "h"]).select(F.col("x.node").alias("a"), F.col("y.node").alias("b"))
    links = _verified(stars.union(pairs).where("a < b").distinct(), sets, threshold).checkpoint()
    roots = components(links)
    large = told.where(F.col("n") > bucket_cap).select("band", "h", "node", "n").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    mixed = large.withColumns({"r": F.min("root").over(w), "t": F.max("root").over(w)}).where("r <> t")
    parted = mixed.join(sets.select("node", F.size("s").alias("size")), "node").checkpoint()
    if parted.limit(1).count():
        links = links.union(_verified(_across(parted, bucket_cap, threshold), sets, threshold))
        roots = components(links)
    top = nodes.select("d", "node").join(roots, "node", "left").select("d", F.coalesce("root", "node").alias("cluster"))
    return digests.select("doc_id", "d").join(top, "d").select("doc_id", "cluster")


def _verified(candidates: DataFrame, sets: DataFrame, threshold: float) -> DataFrame:
    """The candidates ``a``, ``b`` whose sets of shingles have a Jaccard similarity of ``threshold`` at least."""
    one, two = sets.select(F.col("node").alias("a"), F.col("s").alias("p")), sets.select(F.col("node").alias("b"), F.col("s").alias("q"))
    met = candidates.join(one, "a").join(two, "b")
    both = F.size(F.array_intersect("p", "q"))
    return met.where(both / (F.size("p") + F.size("q") - both) >= threshold).select("a", "b")


def _across(members: DataFrame, block: int, threshold: float) -> DataFrame:
    """Pairs ``a`` < ``b`` of each bucket's ``members(band, h, node, n, root, size)`` that have different roots; sizes too far apart for the threshold are left out.

    Members are dealt into blocks by hash; each two blocks of a bucket are a key of the join of their own.
    """
    blocks = F.ceil(F.col("n") / block)
    dealt = members.withColumn("at", F.pmod(F.xxhash64("node", "band"), blocks)).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), blocks - 1)))
    keyed = dealt.select("band", "h", F.least("at", "other").alias("i"), F.greatest("at", "other").alias("j"), "at", "node", "root", "size")
    x, y = keyed.where("at = i").alias("x"), keyed.where("at = j").alias("y")
    near = F.least("x.size", "y.size") >= threshold * F.greatest("x.size", "y.size") - 1e-6
    met = x.join(y, ["band", "h", "i", "j"]).where((F.col("x.root") != F.col("y.root")) & near)
    return met.select(F.least("x.node", "y.node").alias("a"), F.greatest("x.node", "y.node").alias("b")).distinct()


def components(links: DataFrame, rounds: int = 40) -> DataFrame:
    """``node`` and ``root`` for links ``a`` < ``b``: each round takes the least root among neighbours, then that root's own root; rounds are checkpointed."""
    shared_folder(links.sparkSession)
    links = links.checkpoint()
    both = links.union(links.select("b", "a")).toDF("node", "other")
    state = both.groupBy("node").agg(F.least(F.col("node"), F.min("other")).alias("root")).checkpoint()
    for _ in range(rounds):
        near = both.join(state.select(F.col("node").alias("other"), F.col("root").alias("r")), "other").groupBy("node").agg(F.min("r").alias("r"))
        better = state.join(near, "node").select("node", F.col("root").alias("old"), F.least("root", "r").alias("root"))
        jump = better.select(F.col("node").alias("root"), F.col("root").alias("up"))
        new = better.join(jump, "root", "left").select("node", "old", F.least(F.coalesce("up", "root"), "root").alias("root")).checkpoint()
        if not new.where("old <> root").limit(1).count():
            return new.select("node", "root")
        state = new.select("node", "root")
    raise RuntimeError("components did not settle")
