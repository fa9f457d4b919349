"""URL filters: rules by host and path, and a Bloom filter cascade that answers list membership exactly.

Level 0 of a cascade holds the listed keys; each later level holds the keys of the other side that the
level before lets through by mistake, until there are none. Over the complete universe of keys that it was
built for, membership is exact: the first level that refuses a key decides by its parity. Filters are
built by Spark (bitmap aggregates of 32,768 bits) and sent to workers only while all levels stay below
``MAX_BITS``; beyond that, or where the list is that large, membership comes from a join.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from .common import mix, scratch, store

MAX_BITS = 1 << 30
#: Parts that a host's rows are dealt to where membership comes by a join.
SALTS = 16
_CHUNK = 32_768
_URL = r"(?s)^.*?://([^/?#]*)([^?#]*)"
#: Rules of the query: (host, path prefix, verdict).
RULES = (("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block"))
#: The query's list: labels of blocked domains; their subdomains hold the label too.
LISTED = ("casino-win", "free-bets", "cheap-pills", "ads-track")


def host_of(url: Column) -> Column:
    """What stands between the first :// and the next / ? # or the end, A-Z in lower case; empty without ://."""
    return F.translate(F.coalesce(F.regexp_extract(url, _URL, 1), F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def path_of(url: Column) -> Column:
    """What follows the host up to ? # or the end."""
    return F.coalesce(F.regexp_extract(url, _URL, 2), F.lit(""))


def rule_of(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule (host and path written together) that fits, or null; of equally long ones the first by text."""
    found = F.lit(None).cast("string")
    for h, p, _ in sorted(rules, key=lambda r: (-len(r[0] + r[1]), r[0] + r[1]), reverse=True):
        found = F.when(((host == h) | host.endswith("." + h)) & path.startswith(p), F.lit(h + p)).otherwise(found)
    return found


@dataclass(frozen=True)
class Level:
    bits: int
    hashes: int
    seed: int
    data: np.ndarray  # bytes, most significant byte order of bits is little

    def probe(self, one: np.ndarray, two: np.ndarray) -> np.ndarray:
        found = np.ones(len(one), bool)
        for j in range(self.hashes):
            at = positions(one, two, self.seed, j, self.bits)
            found &= (self.data[at >> np.uint64(3)] >> (at & np.uint64(7)).astype(np.uint8) & 1).astype(bool)
        return found


def positions(one: np.ndarray, two: np.ndarray, seed: int, j: int, bits: int) -> np.ndarray:
    """The bit of hash j of a level for keys with these two 64-bit hashes."""
    with np.errstate(over="ignore"):
        start = mix(one, np.uint64(seed) + two)
        return (start + np.uint64(j) * (mix(two, start) | np.uint64(1))) % np.uint64(bits)


def _hashes(key: Column) -> list[Column]:
    return [F.xxhash64(key, F.lit(0)), F.xxhash64(F.lit(1), key)]


def _unsigned(x: pd.Series) -> np.ndarray:
    return x.to_numpy().astype(np.int64).view(np.uint64)


def level_size(n: int, rate: float) -> tuple[int, int]:
    """Bits and hashes of a filter of ``n`` keys at a false positive rate."""
    return max(64, math.ceil(n * math.log2(1 / rate) / math.log(2))), max(1, round(math.log2(1 / rate)))


def build_level(keys: DataFrame, n: int, rate: float, seed: int) -> Level:
    """A Bloom filter of the ``n`` keys of ``keys(one, two)`` at the false positive rate asked for; its bitmaps come to the driver."""
    bits, hashes = level_size(n, rate)

    @pandas_udf("array<bigint>")
    def spots(one: pd.Series, two: pd.Series) -> pd.Series:
        a, b = _unsigned(one), _unsigned(two)
        return pd.Series(list(np.stack([positions(a, b, seed, j, bits) for j in range(hashes)], 1).astype(np.int64)))

    at = keys.select(F.explode(spots("one", "two")).alias("at"))
    maps = at.groupBy((F.col("at") / _CHUNK).cast("int").alias("chunk")).agg(F.bitmap_construct_agg(F.col("at") % _CHUNK).alias("map"))
    data = np.zeros(-(-bits // _CHUNK) * _CHUNK // 8, np.uint8)
    for chunk, part in maps.toLocalIterator():
        data[chunk * _CHUNK // 8 : (chunk + 1) * _CHUNK // 8] = np.frombuffer(part, np.uint8)
    return Level(bits, hashes, seed, data)


def _ask(levels: list[Level], one: np.ndarray, two: np.ndarray) -> np.ndarray:
    """Membership by the first level that refuses a key, or by the last one's side."""
    out, going = np.full(len(one), len(levels) % 2 == 1), np.arange(len(one))
    for i, level in enumerate(levels):
        hit = level.probe(one[going], two[going])
        out[going[~hit]] = i % 2 == 1
        going = going[hit]
    return out


def member(levels: list[Level], key: Column) -> Column:
    """Exact membership of a key of the universe, by the cascade alone."""
    if not levels:
        return F.lit(False)

    @pandas_udf("boolean")
    def test(one: pd.Series, two: pd.Series) -> pd.Series:
        return pd.Series(_ask(levels, _unsigned(one), _unsigned(two)))

    return test(*_hashes(key))


def any_member(levels: list[Level], keys: Column) -> Column:
    """Whether a key of an array is a member; all keys must be of the universe."""
    if not levels:
        return F.lit(False)

    @pandas_udf("boolean")
    def test(one: pd.Series, two: pd.Series) -> pd.Series:
        size = one.map(len).to_numpy().astype(np.int64)
        if not size.sum():
            return pd.Series(np.zeros(len(size), bool))
        flat = _ask(levels, *(np.concatenate(x.to_numpy()).astype(np.int64).view(np.uint64) for x in (one, two)))
        return pd.Series(np.bincount(np.repeat(np.arange(len(size)), size), flat, minlength=len(size)) > 0)

    return test(F.transform(keys, lambda k: _hashes(k)[0]), F.transform(keys, lambda k: _hashes(k)[1]))


def build_cascade(universe: DataFrame, *, max_levels: int = 64, max_bits: int = MAX_BITS) -> list[Level] | None:
    """Levels over ``universe(key string, listed boolean)``, keys distinct and not null; null where all levels together would pass ``max_bits``.

    The universe lies in a shared table while levels are built; each level's mistakes are found in
    the workers, and only counts and bitmaps reach the driver.
    """
    spark = universe.sparkSession
    universe = store(universe.select("listed", *[h.alias(n) for h, n in zip(_hashes(F.col("key")), ("one", "two"))]), scratch(spark, "cascade-universe"))
    n, listed = universe.agg(F.count(F.lit(1)), F.count_if("listed")).first()
    levels: list[Level] = []
    holds, other, size, others = universe.where("listed"), universe.where("not listed"), listed, n - listed
    while size and len(levels) < max_levels:
        rate = 0.5 if levels else min(0.5, max(1e-6, size * math.sqrt(0.5) / max(others, 1)))
        if sum(x.bits for x in levels) + level_size(size, rate)[0] > max_bits:
            return None
        levels.append(build_level(holds, size, rate, len(levels)))
        mistaken = store(_let_through(other, levels[-1]), scratch(spark, "cascade-level"))
        holds, other, size, others = mistaken, holds, mistaken.count(), size
    if size:
        raise RuntimeError("cascade did not end")
    return levels


def _let_through(keys: DataFrame, level: Level) -> DataFrame:
    @pandas_udf("boolean")
    def test(one: pd.Series, two: pd.Series) -> pd.Series:
        return pd.Series(level.probe(_unsigned(one), _unsigned(two)))

    return keys.select("one", "two").where(test("one", "two"))


def labels_of(host: Column) -> Column:
    """The labels of a host but the last, each once: what a list of domain labels is asked for."""
    return F.array_distinct(F.filter(F.regexp_extract_all(host, F.lit(r"([^.]+)\.")), lambda x: x != ""))


def judge(pages: DataFrame, listed: DataFrame, keys_of=labels_of, *, rules=RULES, max_bits: int = MAX_BITS) -> DataFrame:
    """``page_id``, ``host``, ``path``, ``rule`` and ``verdict`` of every row.

    ``listed(key)`` is the list, a table of any size; ``keys_of`` gives the keys of a host, of which one must be listed to block it.
    The universe is all keys of all hosts. Its cascade answers while it stays below ``max_bits``; beyond that the distinct blocked hosts are
    joined back, salted, as one host may hold a third of all rows. Null urls and those without :// have empty host and
    path, no key, and are judged by the rules like any other; repeated rows are answered each; an empty table gives an empty one, an
    empty list blocks by rules alone; other columns are left behind, whatever their names.
    """
    split = pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    ruled = split.withColumn("rule", rule_of(F.col("host"), F.col("path"), rules))
    hosts = split.select("host").distinct()
    keys = hosts.select(F.explode(keys_of(F.col("host"))).alias("key")).distinct()
    known = listed.select("key").where("key is not null").distinct().withColumn("listed", F.lit(True))
    levels = build_cascade(keys.join(known, "key", "left").select("key", F.coalesce("listed", F.lit(False)).alias("listed")), max_bits=max_bits)
    if levels is not None:
        ruled = ruled.withColumn("blocked", any_member(levels, keys_of(F.col("host"))))
    else:
        hit = hosts.select("host", F.explode(keys_of(F.col("host"))).alias("key")).join(known, "key").select("host").distinct()
        hit = hit.select("host", F.lit(True).alias("blocked"), F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
        salted = ruled.withColumn("salt", F.pmod(F.xxhash64("page_id", "path"), F.lit(SALTS)).cast("int"))
        ruled = salted.join(hit, ["host", "salt"], "left")
    own = F.when(F.col("blocked"), "block").otherwise("allow")
    verdicts = F.create_map(*[F.lit(x) for h, p, v in rules for x in (h + p, v)]) if rules else None
    return ruled.select("page_id", "host", "path", "rule", (F.coalesce(F.element_at(verdicts, F.col("rule")), own) if rules else own).alias("verdict"))


def block_list(spark: SparkSession, labels: tuple[str, ...] = LISTED) -> DataFrame:
    """A list of domain labels as a table."""
    return spark.createDataFrame([(x,) for x in labels], "key string")


SQL = rf"""
WITH split AS (
  SELECT page_id,
         translate(coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', 1), ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', 2), '') AS path
  FROM pages),
rules(h, p, v) AS (VALUES {", ".join(f"('{h}', '{p}', '{v}')" for h, p, v in RULES)}),
fits AS (
  SELECT page_id, max_by(h || p, length(h || p)) AS rule, max_by(v, length(h || p)) AS v
  FROM split JOIN rules ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p) GROUP BY page_id)
SELECT s.page_id, s.host, s.path, f.rule,
       coalesce(f.v, CASE WHEN regexp_matches(s.host, '(^|\.)({'|'.join(LISTED)})\.') THEN 'block' ELSE 'allow' END) AS verdict
FROM split s LEFT JOIN fits f USING (page_id)
"""
