"""SimHash near-duplicates by anchor-point covering.

The 64 bits fall into three blocks; fingerprints at 4 or fewer differing bits agree but for one bit at
most in one of them. In each block the perfect (23, 12) Golay code, shortened where the block is
smaller, gives the anchors: every point lies within ``RADIUS`` = 3 of one. A fingerprint has one home
anchor in a block and is replicated to every anchor within RADIUS + 1, so a pair that agrees but for one bit in a
block meets at a home anchor, and pairs are compared there, on all 64 bits. Fingerprints are compared
once each, whatever the number of documents that share them. Links are never stored one by one: a first pass gives every
fingerprint its number of links and its least neighbour, whose pointers make trees; a second pass reports links between different
trees alone, from which components come.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import ensure_checkpoint_dir, scratch, slices, store, utf8
from .components import SALTS, components, look_up, roots_of

SHINGLE, THRESHOLD, SEED = 4, 4, 42
#: Start bit and width of each block.
BLOCKS = ((0, 22), (22, 21), (43, 21))
RADIUS, SLACK = 3, 1
#: Generator polynomial of the binary Golay code and its length.
GENERATOR, LENGTH = 0b101011100011, 23


def fingerprint(text: bytes) -> int:
    """Unsigned SimHash of a text's word shingles; no word gives 0."""
    words = text.lower().split()
    if not words:
        return 0
    if len(words) <= SHINGLE:
        hashes = [xxhash.xxh64_intdigest(b" ".join(words), SEED)]
    else:
        joined, one = b" ".join(words), xxhash.xxh64_intdigest
        ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
        starts = [0, *(ends[: len(words) - SHINGLE] + 1).tolist()]
        hashes = [one(joined[a:b], SEED) for a, b in zip(starts, ends[SHINGLE - 1 :].tolist())]
    bits = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 1 << 16):
        part = np.array(hashes[i : i + (1 << 16)], np.uint64)
        bits += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * bits > len(hashes), bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame, *, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key``, ``h`` (a hash of the text) and ``fp`` (the fingerprint's bits as a signed long) of each row; null text counts as empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 1):
            known: dict[bytes, int] = {}
            out = np.array([known[x] if x in known else known.setdefault(x, fingerprint(x)) for x in utf8(b.column(1)).to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(out.view(np.int64))], ["key", "h", "fp"])

    docs = docs.select(F.col(key), F.col(text), F.xxhash64(text))
    return docs.mapInArrow(run, f"`{key}` {docs.schema[0].dataType.simpleString()}, h bigint, fp bigint")


def syndrome(points: np.ndarray) -> np.ndarray:
    """Remainder of 23-bit points by the generator polynomial."""
    out = points.copy()
    for i in range(LENGTH - 1, 10, -1):
        out = np.where(out >> i & 1, out ^ (GENERATOR << (i - 11)), out)
    return out


@lru_cache(maxsize=1)
def _leaders() -> tuple[np.ndarray, dict[int, np.ndarray]]:
    """By syndrome: the one error pattern of weight 3 or less, and all those of weight 4 that have it."""
    home, four = np.zeros(1 << 11, np.int64), {}
    for weight in range(RADIUS + 1):
        patterns = np.array([sum(1 << i for i in c) for c in combinations(range(LENGTH), weight)], np.int64)
        home[syndrome(patterns)] = patterns
    patterns = np.array([sum(1 << i for i in c) for c in combinations(range(LENGTH), RADIUS + SLACK)], np.int64)
    found = syndrome(patterns)
    order = np.argsort(found, kind="stable")
    for s, part in zip(*np.unique(found[order], return_index=True)):
        four[int(s)] = part
    bounds = np.append(np.unique(found[order], return_index=True)[1], len(order))
    return home, {s: patterns[order[bounds[i] : bounds[i + 1]]] for i, s in enumerate(sorted(four))}


def anchors(fp: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Index of the fingerprint, anchor number (its block included) and whether it is home, for every replica.

    An anchor within RADIUS + 1: the home codeword, and all codewords at 4. Errors in a shortened block's
    missing bits stay allowed, which can only add anchors.
    """
    home, four = _leaders()
    index, anchor, is_home = [], [], []
    for k, (start, width) in enumerate(BLOCKS):
        points = (fp >> np.uint64(start)).astype(np.int64) & ((1 << width) - 1)
        s = syndrome(points)
        index.append(np.arange(len(fp)))
        anchor.append(points ^ home[s] | k << LENGTH)
        is_home.append(np.ones(len(fp), bool))
        for value in np.unique(s):
            if (more := four.get(int(value))) is not None:
                rows = np.flatnonzero(s == value)
                index.append(np.repeat(rows, len(more)))
                anchor.append((points[rows, None] ^ more[None, :] | k << LENGTH).ravel())
                is_home.append(np.zeros(len(rows) * len(more), bool))
    return np.concatenate(index), np.concatenate(anchor), np.concatenate(is_home)


def replicate(fps: DataFrame) -> DataFrame:
    """``fp``, ``root`` (carried along), ``anchor`` and ``home`` for each distinct fingerprint of ``fps(fp, root)`` and each anchor in reach."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp, root = np.asarray(b.column(0)).view(np.uint64), np.asarray(b.column(1))
            for i in range(0, len(fp), 50_000):
                part, its = fp[i : i + 50_000], root[i : i + 50_000]
                index, anchor, home = anchors(part)
                yield pa.RecordBatch.from_arrays([pa.array(part[index].view(np.int64)), pa.array(its[index]), pa.array(anchor), pa.array(home)], ["fp", "root", "anchor", "home"])

    return fps.select("fp", "root").mapInArrow(run, "fp bigint, root bigint, anchor bigint, home boolean")


#: Comparisons for each fingerprint beyond which anchors are split by an equal part as well.
LOAD = 4_000
#: Parts for that: of five, one has none of the four differing bits.
PARTS = ((0, 13), (13, 13), (26, 13), (39, 13), (52, 12))


def _bits(x: Column, start: int, width: int) -> Column:
    return F.shiftrightunsigned(x, start).bitwiseAND(F.lit((1 << width) - 1))


def load(reached: DataFrame) -> int:
    """Comparisons that whole anchors would take, from the members of each (at most 3 * 4096 anchors); their counts are added up inside tasks first."""
    sizes = reached.groupBy("anchor").agg(F.count_if("home").alias("h"), F.count(F.lit(1)).alias("n"))
    return int(sizes.agg(F.sum(F.col("h").cast("double") * F.col("n"))).first()[0] or 0)


def links(fps: DataFrame, *, split: bool = False) -> DataFrame:
    """All pairs ``a`` < ``b`` of distinct fingerprints at THRESHOLD or fewer differing bits, once each; of ``fps(fp, root)`` with their roots ``ra`` and ``rb``.

    A pair is reported only at the first block (and part) in which it can meet.
    """
    rooted = "root" in fps.columns
    reached = replicate(fps if rooted else fps.select("fp", F.col("fp").alias("root")))
    if split:
        parts = F.array(*[F.struct(F.lit(i).alias("part"), _bits(F.col("fp"), *p).alias("value")) for i, p in enumerate(PARTS)])
        reached = reached.select("*", F.inline(parts))
    on = ["anchor", "part", "value"] if split else ["anchor"]
    one = reached.where("home").select(*on, F.col("fp").alias("a"), F.col("root").alias("ra"))
    two = reached.select(*on, F.col("fp").alias("b"), F.col("root").alias("rb"))
    differs, block = F.col("a").bitwiseXOR(F.col("b")), F.shiftright("anchor", LENGTH)
    first = F.lit(True)
    for k, (start, width) in enumerate(BLOCKS):
        near = F.bit_count(_bits(differs, start, width)) <= SLACK
        first = first & F.when(block == k, near).when(block > k, ~near).otherwise(True)
    if split:
        for i, (start, width) in enumerate(PARTS[:-1]):
            first = first & ((F.col("part") <= i) | (_bits(differs, start, width) != 0))
    met = one.join(two, on)
    return met.where((F.col("a") < F.col("b")) & (F.bit_count(differs) <= THRESHOLD) & first).select("a", "b", *(("ra", "rb") if rooted else ()))


def duplicate_classes(docs: DataFrame, *, most: int = LOAD) -> tuple[DataFrame, DataFrame]:
    """(rows, classes): ``doc_id, h, fp`` of every row, and ``fp, component_id, links`` of every distinct fingerprint.

    ``component_id`` is the smallest doc_id reachable (null where all are null), ``links`` the number of
    other fingerprints linked directly, ``h`` a hash of the text. Both results lie in the shared folder.
    """
    ensure_checkpoint_dir(docs.sparkSession)
    rows = _written(fingerprints(docs.select("doc_id", "text")), "simhash-rows")
    nodes = rows.groupBy("fp").agg(F.min("doc_id").alias("first"))
    alone = _written(nodes.select("fp", F.col("fp").alias("root"), "first"), "simhash-nodes")
    split = load(replicate(alone)) > most * alone.count()
    both = links(alone, split=split).select(F.inline(F.array(F.struct(F.col("a").alias("fp"), F.col("b").alias("other")), F.struct(F.col("b").alias("fp"), F.col("a").alias("other")))))
    near = _written(both.groupBy("fp").agg(F.count(F.lit(1)).alias("links"), F.min("other").alias("other")), "simhash-near")
    trees = roots_of(near.select(F.col("fp").alias("node"), F.least("fp", "other").alias("root")))
    across = links(trees.withColumnRenamed("node", "fp"), split=split).where("ra <> rb").select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct()
    joined = components(_written(across, "simhash-across"))
    linked = look_up(trees, "root", joined, "top").select(F.col("node").alias("fp"), F.col("top").alias("root"))
    told = alone.select("fp", "first").join(linked, "fp", "left").join(near.select("fp", "links"), "fp", "left")
    told = _written(told.select("fp", "first", F.coalesce("root", "fp").alias("root"), F.coalesce("links", F.lit(0).cast("long")).alias("links")), "simhash-told")
    least = told.groupBy("root").agg(F.min("first").alias("component_id"), F.count(F.lit(1)).alias("n"))
    wide = least.where("n > 1").select(F.col("root").alias("_root"), "component_id", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("_part"))
    salted = told.withColumn("_salt", F.pmod(F.xxhash64("fp"), F.lit(SALTS)).cast("int"))
    met = salted.join(wide, (F.col("root") == F.col("_root")) & (F.col("_salt") == F.col("_part")), "left")
    return rows, met.select("fp", F.when(F.col("_root").isNull(), F.col("first")).otherwise(F.col("component_id")).alias("component_id"), "links")


def _written(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a table in the shared folder: computed once, and safe from lost executors."""
    return store(df, scratch(df.sparkSession, name))


def near_duplicates(docs: DataFrame) -> DataFrame:
    """``doc_id``, ``fingerprint`` (hexadecimal), ``component_id`` and ``links`` of every row.

    Null and empty texts have fingerprint 0 and are linked like any other; long texts count whole. Repeated rows are answered
    each; an empty table gives an empty one; other columns are left behind, whatever their names.
    """
    rows, classes = duplicate_classes(docs)
    return rows.join(classes, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "links")


def keep_one(docs: DataFrame) -> DataFrame:
    """The rows of ``docs``, one for each component: that of the smallest doc_id (null last), then of the smallest text hash.

    All columns stay as they are, whatever their names. Null and empty texts have fingerprint 0 and are one component; of rows equal in id
    and text one stays, the first by its other columns; an empty table gives an empty one.
    """
    rows, classes = duplicate_classes(docs)
    place = F.struct(F.col("doc_id").isNull().alias("n"), F.col("doc_id"), F.col("h"))
    kept = rows.join(classes, "fp").groupBy(F.coalesce("component_id", "fp").alias("c"), F.col("component_id").isNull().alias("u")).agg(F.min(place).alias("p"))
    kept = _written(kept.select(F.col("p.doc_id").alias("id"), F.col("p.h").alias("h")), "simhash-kept")
    whole = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.xxhash64("text").alias("hash"))
    left = whole.join(kept.hint("merge"), F.col("row.doc_id").eqNullSafe(F.col("id")) & (F.col("hash") == F.col("h")), "left_semi")
    twice = rows.join(kept, F.col("doc_id").eqNullSafe(F.col("id")) & (rows["h"] == kept["h"]), "left_semi").groupBy("doc_id", "h").count().where("count > 1")
    if twice.limit(1).count():  # rows repeated as a whole, or but for other columns
        order = Window.partitionBy("row.doc_id", "hash").orderBy(F.to_json("row"))
        left = left.withColumn("n", F.row_number().over(order)).where("n = 1")
    return left.select("row.*")
