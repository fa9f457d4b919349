"""Reproducible shuffle into shards: a Feistel permutation, with cycle walking, of global row numbers.

Row numbers are dense and follow from the rows alone: rows are dealt to ``BUCKETS`` buckets by a hash
of their key and content, counted, and numbered inside their bucket; a row's number is its bucket's
offset plus its rank. The permuted number p gives shard p mod S and slot p div S, so shard sizes
differ by one at most and any (shard, slot) can be computed, or inverted, without the table.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

BUCKETS = 4096
ROUNDS = 6
SEED = 20_240_607


def _round_keys(seed: int) -> list[int]:
    keys, z = [], seed & 0xFFFFFFFFFFFFFFFF
    for _ in range(ROUNDS):
        z = (z * 6364136223846793005 + 1442695040888963407) & 0xFFFFFFFFFFFFFFFF
        keys.append(z ^ (z >> 29))
    return keys


def _halves(n: int) -> tuple[int, np.uint64]:
    """Bits of a half and its mask: the smallest square domain that holds n values, less than 4n."""
    half = max(1, (max(n - 1, 1).bit_length() + 1) // 2)
    return half, np.uint64((1 << half) - 1)


def _stir(x: np.ndarray, key: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        z = (x + np.uint64(key)) * np.uint64(0x9E3779B97F4A7C15)
        z ^= z >> np.uint64(32)
        z *= np.uint64(0xD6E8FEB86659FD93)
        return z ^ (z >> np.uint64(32))


def permute(numbers: np.ndarray, n: int, seed: int = SEED, *, inverse: bool = False) -> np.ndarray:
    """The image of each number under a keyed bijection of [0, n); ``inverse`` gives the number back.

    Values outside [0, n) that the network yields are sent through it again until they fall inside.
    """
    half, mask = _halves(n)
    keys, shift = _round_keys(seed), np.uint64(half)

    def network(x: np.ndarray) -> np.ndarray:
        left, right = x >> shift, x & mask
        for key in reversed(keys) if inverse else keys:
            if inverse:
                left, right = right ^ (_stir(left, key) & mask), left
            else:
                left, right = right, left ^ (_stir(right, key) & mask)
        return left << shift | right

    out = np.asarray(numbers).astype(np.uint64)
    if n <= 1:
        return out.astype(np.int64)
    walking = np.arange(len(out))
    while len(walking):
        out[walking] = network(out[walking])
        walking = walking[out[walking] >= np.uint64(n)]
    return out.astype(np.int64)


def locate(shard: int, slot: int, n: int, shards: int, seed: int = SEED) -> int:
    """The global row number that a shard's slot holds."""
    return int(permute(np.array([slot * shards + shard]), n, seed, inverse=True)[0])


def _numbered(df: DataFrame, by: list[str], buckets: int) -> DataFrame:
    """``row`` (all of ``df``'s columns), ``number`` and ``count``."""
    row = F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row")
    spread = df.select(row, F.pmod(F.xxhash64(*[F.col(f"`{c}`") for c in by]), F.lit(buckets)).cast("int").alias("bucket"))
    counts = spread.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))
    whole = Window.partitionBy(F.lit(0))
    before = whole.orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)
    offsets = counts.select("bucket", (F.sum("n").over(before) - F.col("n")).alias("offset"), F.sum("n").over(whole).alias("count"))
    rank = F.row_number().over(Window.partitionBy("bucket").orderBy(*[F.col("row").getField(c) for c in by]))
    return spread.withColumn("rank", rank).join(F.broadcast(offsets), "bucket").select("row", (F.col("offset") + F.col("rank") - 1).alias("number"), "count")


def number_rows(df: DataFrame, by: list[str], *, buckets: int = BUCKETS) -> DataFrame:
    """Adds ``row_number`` (dense from 0) and ``row_count``; columns of ``df`` with these names are replaced, all others stay.

    ``by`` must tell rows apart; rows equal in all of it are interchangeable. Nulls are values like others. The bucket counts are one small
    table of ``buckets`` rows at most, whatever the table's size.
    """
    df = df.drop(*({"row_number", "row_count"} - set(by)))
    return _numbered(df, by, buckets).select("row.*", F.col("number").alias("row_number"), F.col("count").alias("row_count"))


def assign(df: DataFrame, shards: int, *, seed: int = SEED, by: list[str]) -> DataFrame:
    """``df`` with ``shard`` and ``slot``: the law is ``rows``, counts at most one apart, slots gapless from 0.

    An empty table gives an empty one. Repeated rows get a place each. Columns of ``df`` with the names of the two are replaced, all others stay.
    """

    @pandas_udf("bigint")
    def place(number: pd.Series, count: pd.Series) -> pd.Series:
        return pd.Series(permute(number.to_numpy(), int(count.iloc[0]), seed) if len(number) else number.to_numpy())

    df = df.drop(*({"shard", "slot"} - set(by)))
    placed = _numbered(df, by, BUCKETS).select("row", place("number", "count").alias("place"))
    return placed.select("row.*", F.pmod("place", F.lit(shards)).cast("int").alias("shard"), F.expr(f"place div {int(shards)}").alias("slot"))


def shard_documents(docs: DataFrame, shards: int = 24, seed: int = SEED) -> DataFrame:
    """Shard and slot of every document; size is its UTF-8 bytes (null: none) plus 8.

    Null and empty texts count 8 bytes, a text of any length is one row, equal rows get a place each, null ids are ids like others. An empty
    table gives an empty one; other columns are left behind, whatever their names.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    sized = docs.select("doc_id", (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"))
    placed = assign(sized, shards, seed=seed, by=["doc_id", "text_crc32", "size"])
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
