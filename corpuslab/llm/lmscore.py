"""LM scoring with a log-frequency Bloom filter of quantised n-gram counts.

Counts of words and word pairs over all training documents are quantised on a logarithmic scale; an
n-gram of quantised count q is put into the filter as (n-gram, 1) to (n-gram, q). Asking (n-gram, 1), (n-gram, 2), ...
until one is refused gives its count back, within the scale's step and the filter's error. The filter is
blocked: an n-gram's bits lie in one segment, which one task builds. Its size follows its number of entries at
a fixed error rate. Up to ``MAX_BITS`` it is broadcast; a larger one stays a table of segments, the n-grams that
chunks of texts ask for are shuffled to their segments and the counts joined back.

A token's probability is interpolated: L * c(v, w) / c(v) + (1 - L) * P(w), with P(w) add-one over quantised counts and
their own sum, so that it sums to one, and the pair term's quotients summing to one within the step of the count scale;
a weight L for each quantised count of v, fitted by deleted interpolation (every token left out of its own
counts) on all training documents. The base score needs exact counts: those of the ``HEAD`` most frequent words are broadcast, the
rest come by a join of the rare tokens alone.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Words, mix, row_sums, scratch, slices, store, utf8

#: Step of the count scale; false positives of one question; largest filter that is broadcast.
STEP, RATE, MAX_BITS = 1.5, 1 / 128, 1 << 30
#: Words whose exact counts are broadcast.
HEAD = 1 << 20
#: Bins of log10(pair probability / word probability) that the fit sums up in, and their width.
_BINS, _WIDTH = 200, 0.05
#: Sums of logarithms over a join are taken in whole units of this fineness, so that their order is nothing to them.
_UNITS = 2.0**36
#: Bits of a segment, which one task builds, and of a line of it, the 64 bytes that memory is read by.
SEGMENT, LINE = 1 << 22, 512
_END, _START = np.uint64(0x656E64206F662074), np.uint64(0x7374617274206F66)
TRAIN_SLICE = 8_000_000
#: Tokens whose stored counts are handled at once.
LEVELS_SLICE = 500_000


def is_held_out(doc_id: Column) -> Column:
    """Whether crc32 of the id as text leaves 2 by 7; a null id counts as empty text."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(7)) == 2


@dataclass
class Tokens:
    """Word and end tokens of a slice: hashes of each token, of the one before it, and where texts start."""

    one: np.ndarray
    before: np.ndarray
    starts: np.ndarray

    @classmethod
    def of(cls, texts: pa.Array) -> Tokens:
        words = Words(texts, lower=True)
        ends = words.starts[1:]
        one = np.insert(words.hashes() & ~np.uint64(1), ends, _END)
        starts = words.starts + np.arange(len(words.starts))
        before = np.empty_like(one)
        before[1:] = one[:-1]
        before[starts[:-1]] = _START
        return cls(one, before, starts)

    def owner(self) -> np.ndarray:
        """For each token, the row of its text."""
        return np.repeat(np.arange(len(self.starts) - 1), np.diff(self.starts))

    def pairs(self) -> np.ndarray:
        return mix(self.before, self.one) | np.uint64(1)


def count(docs: DataFrame) -> DataFrame:
    """``key`` and exact count ``c`` of every word (even keys) and word pair (odd keys) of ``docs(text, held_out)`` not held out.

    Keys are 64-bit hashes. Each worker adds up its slices first; Spark adds up the rest, spilling if it must.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 0, TRAIN_SLICE):
            tokens = Tokens.of(b.column(0))
            keys, n = np.unique(np.concatenate([tokens.one, tokens.pairs()]), return_counts=True)
            for i in range(0, len(keys), 100_000):
                yield pa.RecordBatch.from_arrays([pa.array(keys[i : i + 100_000].view(np.int64)), pa.array(n[i : i + 100_000])], ["key", "c"])

    return docs.where("not held_out").select("text").mapInArrow(run, "key bigint, c bigint").groupBy("key").agg(F.sum("c").alias("c"))


def quantise(c: np.ndarray, step: float = STEP) -> np.ndarray:
    return 1 + np.floor(np.log(c) / math.log(step) + 1e-9).astype(np.int64)


def restore(q: np.ndarray, step: float = STEP) -> np.ndarray:
    """A count for each quantised one: the middle of the whole numbers that it stands for, 0 for 0."""
    levels = np.arange(1, 160)
    low = np.ceil(step ** (levels - 1) - 1e-9)
    high = np.maximum(low, np.ceil(step**levels - 1e-9) - 1)
    return np.concatenate([[0.0], (low + high) / 2])[np.minimum(q, 159)]


@dataclass(frozen=True)
class Filter:
    segments: int
    hashes: int
    data: np.ndarray  # packed bits, little bit order

    def counts(self, key: np.ndarray) -> np.ndarray:
        """Quantised count of each key: questions go on, level by level, for the keys that were not refused yet."""
        q, going, level = np.zeros(len(key), np.int64), np.arange(len(key)), 0
        offset = segment(key, self.segments) * np.uint64(SEGMENT)
        while len(going) and level < 150:
            level += 1
            line, bits = places(key[going], level)
            line += offset[going]
            for j in range(self.hashes):
                at = line | inside(bits, j)
                hit = (self.data.take((at >> np.uint64(3)).view(np.int64)) >> (at & np.uint64(7)).astype(np.uint8) & 1).astype(bool)
                going, line, bits = going[hit], line[hit], bits[hit]
            q[going] = level
        return q


@dataclass(frozen=True)
class Spread:
    """A filter too large to broadcast: its segments lie in a stored table."""

    segments: int
    hashes: int
    path: str


@dataclass(frozen=True)
class Answers:
    """What a spread filter answered to one chunk of texts: sorted keys and their quantised counts."""

    key: np.ndarray
    level: np.ndarray

    @classmethod
    def of(cls, key: np.ndarray, level: np.ndarray) -> Answers:
        key, first = np.unique(key, return_index=True)
        return cls(key, level[first])

    def counts(self, key: np.ndarray) -> np.ndarray:
        if not len(self.key):
            return np.zeros(len(key), np.int64)
        at = np.minimum(np.searchsorted(self.key, key), len(self.key) - 1)
        return np.where(self.key[at] == key, self.level[at], 0)


def segment(key: np.ndarray, segments: int) -> np.ndarray:
    return (key >> np.uint64(40)) % np.uint64(segments)


def places(key: np.ndarray, level: np.ndarray | int) -> tuple[np.ndarray, np.ndarray]:
    """For each (key, level) its line inside the segment, at which all its bits lie, so that a question touches memory once; and the bits' source."""
    h = mix(key, np.asarray(level, np.uint64))
    return (h >> np.uint64(20)) & np.uint64(SEGMENT - LINE), mix(h, key)


def inside(bits: np.ndarray, j: int) -> np.ndarray:
    """The bit of hash j in its line."""
    return (bits >> np.uint64(9 * j)) & np.uint64(LINE - 1)


def build_filter(counts: DataFrame, *, rate: float = RATE, max_bits: int = MAX_BITS) -> Filter | Spread:
    """The filter of a stored count table; up to ``max_bits`` its packed segments come to the driver, else they are stored."""
    q = F.floor(F.log(F.col("c").cast("double")) / math.log(STEP) + 1e-9) + 1
    entries = counts.agg(F.sum(q)).first()[0] or 0
    bits = max(SEGMENT, math.ceil(entries * math.log2(1 / rate) / math.log(2)))
    segments, hashes = -(-bits // SEGMENT), max(1, min(7, round(math.log2(1 / rate))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        maps: dict[int, np.ndarray] = {}
        for b in batches:
            key, level = np.asarray(b.column(0)).view(np.uint64), quantise(np.asarray(b.column(1)))
            times = np.repeat(np.arange(len(key)), level)
            first = np.cumsum(level) - level
            each, of = key[times], (np.arange(len(times)) - first[times] + 1).astype(np.uint64)
            place = segment(each, segments).astype(np.int64)
            for s in np.unique(place):
                here = maps.setdefault(int(s), np.zeros(SEGMENT, bool))
                mine = place == s
                line, bits = places(each[mine], of[mine])
                for j in range(hashes):
                    here[line | inside(bits, j)] = True
        for s, here in maps.items():
            yield pa.RecordBatch.from_arrays([pa.array([s]), pa.array([np.packbits(here, bitorder="little").tobytes()], pa.binary())], ["segment", "data"])

    place = F.pmod(F.shiftrightunsigned("key", 40), F.lit(segments))
    built = counts.repartition(segments, place).select("key", "c").mapInArrow(run, "segment bigint, data binary")
    path = scratch(counts.sparkSession, "lm-filter")
    stored = store(built, path)
    if bits > max_bits:
        return Spread(segments, hashes, path)
    data = np.zeros(segments * SEGMENT // 8, np.uint8)
    for s, part in stored.toLocalIterator():  # each segment is one row
        data[s * SEGMENT // 8 : (s + 1) * SEGMENT // 8] = np.frombuffer(part, np.uint8)
    return Filter(segments, hashes, data)


@dataclass(frozen=True)
class Model:
    """What workers need: the filter, exact counts of the most frequent words by hash, and totals."""

    filter: Filter | Spread | Answers
    head: np.ndarray
    head_counts: np.ndarray
    tokens: int
    words: int
    texts: int
    mass: float  # what the restored counts of all words sum up to, each plus one, and one for unknown words

    def exact(self, key: np.ndarray) -> np.ndarray:
        """Exact counts of head words, -1 for others."""
        if not len(self.head):
            return np.full(len(key), -1)
        at = np.minimum(np.searchsorted(self.head, key), len(self.head) - 1)
        return np.where(self.head[at] == key, self.head_counts[at], -1)


def train(docs: DataFrame, *, head: int = HEAD, **options) -> tuple[Model, DataFrame]:
    """The model of ``docs(text, held_out)`` and the stored counts of all words; ``options`` are those of ``build_filter``."""
    counts = store(count(docs), scratch(docs.sparkSession, "lm-counts"))
    words = counts.where("key % 2 = 0")
    n, v = words.agg(F.sum("c"), F.count(F.lit(1))).first()
    most = words.orderBy(F.desc("c"), "key").limit(head).toArrow() if v > head else words.toArrow()
    key, c = most.column("key").to_numpy().view(np.uint64), most.column("c").to_numpy()
    order = np.argsort(key)
    texts = words.where(F.col("key") == F.lit(int(_END.astype(np.int64)))).agg(F.sum("c")).first()[0]
    levels = words.groupBy((F.floor(F.log(F.col("c").cast("double")) / math.log(STEP) + 1e-9) + 1).cast("int").alias("q")).count().collect()  # 160 rows at most
    mass = 1.0 + sum((float(restore(np.array([q]))[0]) + 1) * k for q, k in levels)
    return Model(build_filter(counts, **options), key[order], c[order], n or 0, v or 0, texts or 0, mass), words


def read_slice(texts: pa.Array, model: Model) -> dict[str, np.ndarray | pa.Array]:
    """For each text: counts, base score of head words, the tokens whose exact count is still to be asked, and a byte for each token's and each pair's quantised count."""
    tokens = Tokens.of(texts)
    code, distinct = pd.factorize(tokens.one)
    pair_code, pairs = pd.factorize(tokens.pairs())
    unknown = model.tokens + model.words + 1
    exact = model.exact(distinct)
    base = np.where(exact >= 0, np.log10((np.maximum(exact, 0) + 1) / unknown), 0.0)
    rare = exact[code] < 0
    if model.words <= len(model.head):  # the head is the whole vocabulary: other tokens are unknown
        base = np.where(exact >= 0, base, np.log10(1 / unknown))
        rare[:] = False
    at = np.concatenate([[0], np.cumsum(rare)])[tokens.starts]
    offsets = pa.py_buffer(tokens.starts.astype("<i4"))
    packed = lambda q: pa.Array.from_buffers(pa.binary(), len(texts), [None, offsets, pa.py_buffer(q.astype(np.uint8))])
    return {
        "n_tokens": np.diff(tokens.starts),
        "known": row_sums((exact > 0)[code], tokens.starts),
        "base": np.bincount(tokens.owner(), base[code], minlength=len(texts)),  # summed text by text, so that equal texts agree to the last bit
        "rare": pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(tokens.one[rare].view(np.int64))),
        "levels": packed(model.filter.counts(distinct)[code]),
        "pair_levels": packed(model.filter.counts(pairs)[pair_code]),
    }


_READ = "n_tokens bigint, known bigint, base double, rare array<bigint>, levels binary, pair_levels binary"


def read(docs: DataFrame, model: Model, shared) -> DataFrame:
    """``read_slice`` of all ``docs(doc_id, text, held_out)``, stored, with a number ``row`` for each row."""
    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, held_out boolean, {_READ}"

    def told(ids, texts, held_out, model: Model) -> tuple[list[pa.Array], list[str]]:
        got = read_slice(texts, model)
        return [ids, held_out, *(pa.array(x) if isinstance(x, np.ndarray) else x for x in got.values())], ["doc_id", "held_out", *got]

    if isinstance(model.filter, Filter):

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in slices(batches, 1):
                yield pa.RecordBatch.from_arrays(*told(b.column(0), b.column(1), b.column(2), shared.value))

        rows = docs.select("doc_id", "text", "held_out").mapInArrow(run, schema)
    else:

        def joined(texts: pa.Table, answers: pa.Table) -> pa.Table:
            flat = [texts.column(c).combine_chunks() for c in ("doc_id", "text", "held_out")]
            key, level = answers.column("key").to_numpy().view(np.uint64), answers.column("level").to_numpy()
            return pa.Table.from_arrays(*told(*flat, replace(shared.value, filter=Answers.of(key, level))))

        texts = _chunks(docs)
        rows = texts.groupBy("chunk").cogroup(ask(texts, model.filter).groupBy("chunk")).applyInArrow(joined, schema)
    return store(rows.withColumn("row", F.monotonically_increasing_id()), scratch(docs.sparkSession, "lm-levels"))


def _chunks(docs: DataFrame) -> DataFrame:
    """``docs`` stored with the number of a chunk of about a slice's bytes."""
    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, text string, held_out boolean, chunk bigint"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = TaskContext.get().partitionId() << 33
        for n, b in enumerate(slices(batches, 1)):
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(np.full(b.num_rows, first + n))], ["doc_id", "text", "held_out", "chunk"])

    return store(docs.select("doc_id", "text", "held_out").mapInArrow(run, schema), scratch(docs.sparkSession, "lm-chunks"))


def ask(texts: DataFrame, filter: Spread) -> DataFrame:
    """``chunk``, ``key`` and ``level`` of the n-grams of ``texts(chunk, text)`` that the filter knows; each segment meets the keys asked of it in one task."""

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 1):
            chunk = np.asarray(b.column(0))
            for c in np.unique(chunk):
                tokens = Tokens.of(b.column(1).filter(pa.array(chunk == c)))
                key = np.unique(np.concatenate([tokens.one, tokens.pairs()]))
                for i in range(0, len(key), 100_000):
                    part = key[i : i + 100_000]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), c)), pa.array(part.view(np.int64)), pa.array(segment(part, filter.segments).astype(np.int64))], ["chunk", "key", "segment"])

    def answer(asked: pa.Table, held: pa.Table) -> pa.Table:
        chunk, key = asked.column("chunk").to_numpy(), asked.column("key").to_numpy().view(np.uint64)
        level = np.zeros(len(key), np.int64)
        one, code = np.unique(key, return_inverse=True)
        for part in held.column("data"):
            level = np.maximum(level, Filter(1, filter.hashes, np.frombuffer(part.as_py(), np.uint8)).counts(one)[code])
        known = level > 0
        return pa.table({"chunk": chunk[known], "key": key[known].view(np.int64), "level": level[known]})

    asked = texts.select("chunk", "text").mapInArrow(keys, "chunk bigint, key bigint, segment bigint")
    held = texts.sparkSession.read.schema("segment bigint, data binary").parquet(filter.path)
    return asked.groupBy("segment").cogroup(held.groupBy("segment")).applyInArrow(answer, "chunk bigint, key bigint, level bigint")


def _counts(b: pa.RecordBatch, model: Model):
    """Where texts start in a batch of ``levels, pair_levels``, and for each token its count, its pair's count, and the quantised and restored count of v."""
    words, pairs = utf8(b.column(0)), utf8(b.column(1))
    bounds = np.asarray(words.buffers()[1]).view("<i8")[words.offset : words.offset + len(words) + 1]
    starts, n = bounds - bounds[0], bounds[-1] - bounds[0]
    begin = np.asarray(pairs.buffers()[1]).view("<i8")[pairs.offset]
    q, pair_q = np.frombuffer(words.buffers()[2], np.uint8)[bounds[0] : bounds[-1]].astype(np.int64), np.frombuffer(pairs.buffers()[2], np.uint8)[begin : begin + n]
    word = restore(q)
    before_q, before = np.empty_like(q), np.empty_like(word)
    before_q[1:], before[1:] = q[:-1], word[:-1]
    before_q[starts[:-1]], before[starts[:-1]] = quantise(np.array([max(model.texts, 1)]))[0], model.texts
    return starts, word, np.minimum(restore(pair_q), np.minimum(word, before)), before_q, before


def ratios(rows: DataFrame, model: Model, shared) -> np.ndarray:
    """Tokens of all training documents, by quantised count of the word before and log ratio of pair to word probability.

    Each token's own occurrence is taken off its counts; workers sum up, and the size of the result is fixed.
    """
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(160 * _BINS, np.int64)
        for b in slices(batches, 0, LEVELS_SLICE):
            m = shared.value
            _, word, both, q, before = _counts(b, m)
            pair = np.maximum(both - 1, 0) / np.maximum(before - 1, 1)
            uni = np.maximum(word, 1) / m.mass
            with np.errstate(divide="ignore"):
                at = np.clip(np.round(np.log10(pair / uni) / _WIDTH) + _BINS // 2, 0, _BINS - 1)
            seen += np.bincount(q * _BINS + np.where(pair > 0, at, 0).astype(np.int64), minlength=len(seen))
        cell = np.flatnonzero(seen)
        yield pa.RecordBatch.from_arrays([pa.array(cell), pa.array(seen[cell])], ["cell", "n"])

    seen = np.zeros((160, _BINS))
    if not model.tokens:
        return seen
    train = rows.where("not held_out")
    for cell, n in train.select("levels", "pair_levels").mapInArrow(run, "cell bigint, n bigint").groupBy("cell").agg(F.sum("n").alias("n")).collect():
        seen[cell // _BINS, cell % _BINS] += n
    return seen


def tune(seen: np.ndarray) -> np.ndarray:
    """Weights by quantised count of the word before, by expectation maximisation over the histogram of ``ratios``."""
    weights = np.full(160, 0.05)
    if not seen.sum():
        return weights
    ratio = 10.0 ** ((np.arange(_BINS) - _BINS // 2) * _WIDTH)
    ratio[0] = 0.0
    near = seen + 20.0 * seen.sum(axis=0) / max(seen.sum(), 1.0)  # counts of thin rows lean on all rows
    for k in range(160):
        x = 0.3
        for _ in range(60):
            x = float((near[k] * (x * ratio / (x * ratio + 1 - x))).sum() / near[k].sum())
        weights[k] = min(max(x, 1e-6), 1 - 1e-6)
    return weights


def score(docs: DataFrame, **options) -> DataFrame:
    """Every document's token counts, exact base score and model score; see the module for the model. ``options`` are those of ``train``.

    Null and empty texts are one end token; texts of any length count whole. Equal texts score alike to the last bit; repeated rows are
    answered each. An empty table gives an empty one; other columns are left behind, whatever their names.
    """
    spark = docs.sparkSession
    docs = docs.select("doc_id", "text", is_held_out(F.col("doc_id")).alias("held_out"))
    model, words = train(docs, **options)
    shared = spark.sparkContext.broadcast(model)
    rows = read(docs, model, shared)
    small = spark.sparkContext.broadcast(replace(model, filter=None, head=model.head[:0], head_counts=model.head_counts[:0]))
    weights = tune(ratios(rows, model, small))
    unknown = float(model.tokens + model.words + 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 0, LEVELS_SLICE):
            starts, word, both, q, before = _counts(b, small.value)
            weight = weights[np.minimum(q, 159)]
            log = np.log10(weight * both / np.maximum(before, 1) + (1 - weight) * (word + 1) / model.mass)
            total = np.bincount(np.repeat(np.arange(b.num_rows), np.diff(starts)), log, minlength=b.num_rows)
            yield pa.RecordBatch.from_arrays([*b.columns[2:], pa.array(total)], [*b.schema.names[2:], "score"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    scored = rows.select("levels", "pair_levels", "doc_id", "held_out", "n_tokens", "known", "base", "row").mapInArrow(run, f"doc_id {kind}, held_out boolean, n_tokens bigint, known bigint, base double, row bigint, score double")
    if model.words <= len(model.head):
        full = scored.select("*", F.lit(0).cast("long").alias("more"), F.lit(0.0).alias("extra"))
    else:
        asked = rows.select("row", F.explode("rare").alias("key"))
        found = asked.join(words, "key", "left").groupBy("row").agg(F.count("c").alias("more"), (F.sum(F.round(F.log10((F.coalesce("c", F.lit(0)) + 1) / unknown) * _UNITS).cast("long")) / _UNITS).alias("extra"))
        full = scored.join(found, "row", "left")
    return full.select(
        "doc_id",
        "held_out",
        "n_tokens",
        (F.col("known") + F.coalesce("more", F.lit(0))).alias("n_known"),
        F.lit(model.tokens).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("extra", F.lit(0.0))).alias("base_score"),
        "score",
    )
