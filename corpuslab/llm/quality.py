"""Quality rules: hashed n-gram log-likelihood ratio between a trusted target and the raw corpus.

Two multinomials over hashed word n-grams (orders 1 and 2, ASCII lower case, ``BUCKETS`` each) are counted:
the target over all trusted labelled documents but every fourth, the raw one over every document. A bucket's weight is
log((t + K) / (e + K)), with t its target count, e the count that its raw share predicts and K a constant
of its order that keeps rare buckets near 0. A document's score is the sum of its n-grams' weights over
its number of words, less the median of clean documents of its language, so that it is compared
inside its language. One threshold decides every document; medians and threshold are calibrated on
all labelled documents that the target does not hold, from counts of their scores in fine steps. The base rules count words, symbols, repeated lines and windows exactly.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SPACES, Words, mix, row_sums, slices, utf8

BUCKETS = 1 << 17
#: K of order 1 and order 2.
PRIORS = (4.0, 200.0)
#: Up to so many labelled ids go to all tasks as sorted arrays; beyond it labels are joined to the texts, with the same results.
LOCAL = 8_000_000
#: Scores are counted in steps of one over this, for medians and threshold.
GRID = 1 << 12
#: What a clean document lost weighs against an unclean one kept, when the threshold is set.
CARE = 2.0
OTHER = "\0other"
#: The characters that count as symbols.
SYMBOLS = b"#*$%&|<>"
MIN_WORDS, MAX_REPEATED = 50, 50

_SYMBOL = np.isin(np.arange(256), np.frombuffer(SYMBOLS, np.uint8))
_START = (np.arange(256) & 0xC0) != 0x80
_VISIBLE = _START & ~np.isin(np.arange(256), np.frombuffer(SPACES, np.uint8))


@dataclass(frozen=True)
class Model:
    """Weights of order 1, then of order 2; offsets by language ("" for null, OTHER for those not seen); the least score that is kept."""

    weights: np.ndarray
    offsets: dict[str, float]
    threshold: float


def ngram_buckets(words: Words, buckets: int = BUCKETS) -> tuple[np.ndarray, np.ndarray]:
    """Bucket and row of every word, then of every pair of words of one text (those from ``buckets`` on)."""
    h, row, mask = words.hashes(), words.owner(), np.uint64(buckets - 1)
    inside = row[:-1] == row[1:]
    pairs = (mix(h[:-1], h[1:])[inside] & mask).astype(np.int64) + buckets
    return np.concatenate([(h & mask).astype(np.int64), pairs]), np.concatenate([row, row[:-1][inside]])


def _langs(column: pa.Array) -> list[str]:
    return column.cast(pa.string()).fill_null("").to_pylist()


#: What a labelled document is for: nothing, the target, or the threshold (unclean and clean ones).
NONE, FIT, UNCLEAN, CLEAN = 0, 1, 2, 3


def split_labels(labels: DataFrame) -> DataFrame:
    """``doc_id`` and ``role`` of every labelled document: three of four trusted ones fit the target; the fourth part of all, by id hash, is for the threshold."""
    clean = (F.col("quality") == 1) & (F.col("toxic") == 0)
    each = labels.where("doc_id is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min(F.coalesce(clean, F.lit(False))).alias("clean"))
    test = F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(4)) == 0
    role = F.when(test & F.col("clean"), CLEAN).when(test, UNCLEAN).when(F.col("clean"), FIT)
    return each.select("doc_id", role.cast("int").alias("role")).where("role is not null")


#: Gives the role of each row of a batch.
Roles = Callable[[pa.RecordBatch], np.ndarray]


def with_roles(docs: DataFrame, roles: DataFrame, local: int = LOCAL) -> tuple[DataFrame, Roles]:
    """Id, text and language of each document, and what tells their roles inside a task; beyond ``local`` labelled ids they are joined on as a fourth column.

    No text is shuffled up to that number, and the pass that reads the texts looks the roles up itself: a pass of their own would keep a second worker for each task.
    """
    docs = _columns(docs)
    if roles.count() > local:
        return docs.join(roles, "doc_id", "left").select(*docs.columns, F.coalesce("role", F.lit(NONE)).alias("role")), lambda b: np.asarray(b.column(3))
    known = roles.toArrow()
    ids, kinds = known.column("doc_id").to_numpy(), known.column("role").to_numpy()
    order = np.argsort(ids)
    ids, kinds = ids[order], kinds[order].astype(np.int8)

    def role_of(b: pa.RecordBatch) -> np.ndarray:
        asked = np.asarray(b.column(0).fill_null(np.iinfo(np.int64).min))
        at = np.minimum(np.searchsorted(ids, asked), max(len(ids) - 1, 0))
        role = np.where(ids[at] == asked, kinds[at], NONE) if len(ids) else np.full(len(asked), NONE)
        role[np.asarray(b.column(0).is_null())] = NONE
        return role

    return docs, role_of


def count_buckets(docs: DataFrame, role_of: Roles, *, buckets: int = BUCKETS) -> DataFrame:
    """``bucket``, ``raw`` and ``target`` counts over all documents ``with_roles``; each task adds up its rows first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        raw, target = np.zeros(2 * buckets, np.int64), np.zeros(2 * buckets, np.int64)
        for b in slices(batches, 1):
            words = Words(b.column(1), lower=True)
            bucket, row = ngram_buckets(words, buckets)
            raw += np.bincount(bucket, minlength=2 * buckets)
            good = role_of(b) == FIT
            if good.any():
                target += np.bincount(bucket[good[row]], minlength=2 * buckets)
        used = np.flatnonzero(raw)
        yield pa.RecordBatch.from_arrays([pa.array(used), pa.array(raw[used]), pa.array(target[used])], ["bucket", "raw", "target"])

    return docs.mapInArrow(run, "bucket bigint, raw bigint, target bigint").groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target"))


def _columns(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long"), "text", F.col("lang") if "lang" in docs.columns else F.lit(None).cast("string").alias("lang"))


def fit(docs: DataFrame, labels: DataFrame, *, local: int = LOCAL, buckets: int = BUCKETS) -> Model:
    """Weights of all buckets, medians and threshold, from all labelled documents. At most 2 * ``buckets`` counts, ``local`` ids and counts of scores come to the driver.

    Without trusted text all weights are 0; without labelled documents to calibrate on, the threshold is 0 too, which keeps all.
    """
    told, role_of = with_roles(docs, split_labels(labels), local)
    counts = count_buckets(told, role_of, buckets=buckets).toArrow()
    at = counts.column("bucket").to_numpy()
    raw, target = np.zeros(2 * buckets), np.zeros(2 * buckets)
    raw[at], target[at] = counts.column("raw").to_numpy(), counts.column("target").to_numpy()
    weights = np.zeros(2 * buckets)
    for k, prior in enumerate(PRIORS):
        part = slice(k * buckets, (k + 1) * buckets)
        expected = raw[part] * (target[part].sum() / max(raw[part].sum(), 1.0))
        weights[part] = np.log((target[part] + prior) / (expected + prior)) if target[part].sum() else 0.0
    return calibrate(told, role_of, Model(weights.astype(np.float32), {}, 0.0))


def _median(steps: np.ndarray, n: np.ndarray) -> float:
    """Median of scores counted in ascending steps."""
    total = np.cumsum(n)
    lower, upper = (steps[np.searchsorted(total, k, side="right")] for k in ((total[-1] - 1) // 2, total[-1] // 2))
    return float(lower + upper) / 2


def calibrate(docs: DataFrame, role_of: Roles, model: Model) -> Model:
    """The model with its languages' medians and the threshold that loses least, over all documents ``with_roles`` for it that have the words asked for.

    A document of several rows counts once, with its least score. Scores are counted by language and kind in steps of 1 / ``GRID``. A language with few clean ones takes the median of all.
    """

    def labelled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            role = role_of(b)
            yield pa.RecordBatch.from_arrays([*b.columns[:3], pa.array(role, pa.int32())], ["doc_id", "text", "lang", "role"]).filter(pa.array((role == UNCLEAN) | (role == CLEAN)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(labelled(batches), 1):
            words, lang = Words(b.column(1), lower=True), _langs(b.column(2))
            enough = pa.array(words.counts >= MIN_WORDS)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(lang), b.column(3), pa.array(scores(words, lang, model))], ["doc_id", "lang", "role", "score"]).filter(enough)

    if "role" in docs.columns:
        docs = docs.where(F.col("role").isin(UNCLEAN, CLEAN))
    found = docs.mapInArrow(run, "doc_id bigint, lang string, role int, score double")
    least = found.groupBy("doc_id", "role").agg(F.min(F.struct("score", "lang")).alias("s"))
    rows = least.groupBy("s.lang", "role", F.round(F.col("s.score") * GRID).cast("long").alias("step")).agg(F.count(F.lit(1)).alias("n")).toPandas().sort_values("step")
    is_clean = (rows["role"] == CLEAN).to_numpy()
    if is_clean.all() or not is_clean.any():
        return model
    clean = rows[is_clean]
    by = clean.groupby("step")["n"].sum()
    middle = _median(by.index.to_numpy(), by.to_numpy()) / GRID
    offsets = {lang: _median(x["step"].to_numpy(), x["n"].to_numpy()) / GRID if x["n"].sum() >= 20 else middle for lang, x in clean.groupby("lang")}
    off = rows["step"].to_numpy() / GRID - np.array([offsets.get(x, middle) for x in rows["lang"]])
    cuts, at = np.unique(off, return_inverse=True)
    good, bad = (np.bincount(at[k], rows["n"].to_numpy()[k], len(cuts)) for k in (is_clean, ~is_clean))
    loss = CARE * (np.cumsum(good) - good) / good.sum() + 1 - (np.cumsum(bad) - bad) / bad.sum()
    best = int(np.argmin(loss))
    return replace(model, offsets=offsets | {OTHER: middle}, threshold=float(cuts[best] - 0.5 / GRID if not best else (cuts[best] + cuts[best - 1]) / 2))


def _windows(codes: np.ndarray) -> np.ndarray:
    """One integer for each 3-word window, equal exactly where the windows are."""
    base = int(codes.max()) + 1
    if base >= 1 << 21:
        pair = np.unique(codes[:-1] * base + codes[1:], return_inverse=True)[1][:-1]
        return pair * base + codes[2:]
    return (codes[:-2] * base + codes[1:-1]) * base + codes[2:]


def repeated_words(codes: np.ndarray) -> int:
    """Words that lie in a 3-word window which the text holds twice or more."""
    if len(codes) < 4:
        return 0
    keys = _windows(codes)
    order = np.sort(keys)
    twice = order[1:][order[1:] == order[:-1]]
    if not len(twice):
        return 0
    at = np.searchsorted(twice, keys)
    hit = twice[np.minimum(at, len(twice) - 1)] == keys
    covered = np.zeros(len(codes), bool)
    for k in range(3):
        covered[k : len(hit) + k] |= hit
    return int(covered.sum())


def repeated_lines(text: bytes) -> int:
    if b"\n" not in text:
        return 0
    lines = [x for x in text.split(b"\n") if x.strip()]
    return len(lines) - len(set(lines))


def base_columns(texts: pa.Array) -> dict[str, np.ndarray]:
    """The exact base counts of a slice of texts."""
    words, raw = Words(texts), utf8(texts)
    starts = np.asarray(raw.buffers()[1]).view("<i8")[raw.offset : raw.offset + len(raw) + 1].astype(np.int64)
    data = np.frombuffer(raw.buffers()[2] or b"", np.uint8)[starts[0] : starts[-1]]
    starts = starts - starts[0]
    return {
        "n_words": words.counts,
        "word_chars": row_sums(_VISIBLE[data], starts),
        "n_symbols": row_sums(_SYMBOL[data], starts),
        "n_dup_lines": np.array([repeated_lines(x) for x in raw.to_pylist()], np.int64),
        "n_repeat_words": np.array([repeated_words(words.codes[a:b]) for a, b in zip(words.starts, words.starts[1:])], np.int64),
    }


def scores(words: Words, langs: list[str], model: Model) -> np.ndarray:
    """Each text's score; 0 where it has no word."""
    n = len(words.counts)
    bucket, row = ngram_buckets(words, len(model.weights) // 2)
    mean = np.bincount(row, model.weights[bucket], minlength=n) / np.maximum(words.counts, 1)
    return np.where(words.counts > 0, mean - np.array([model.offsets.get(x, model.offsets.get(OTHER, 0.0)) for x in langs]), 0.0)


def judge(docs: DataFrame, model: Model) -> DataFrame:
    """``docs`` with the base counts, ``base_failed``, ``llr`` and ``kept``; every row is judged by its whole text.

    Null and empty texts have no words and fail; texts of any length count whole. Equal texts of one language get equal verdicts, repeated
    rows are answered each, an empty table gives an empty one. Columns of ``docs`` with the names of new ones are replaced, all others stay.
    """
    new = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "llr", "kept")
    docs = docs.drop(*new)
    names = docs.columns
    text, lang = names.index("text"), names.index("lang") if "lang" in names else -1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, text):
            got = base_columns(b.column(text))
            failed = (got["n_words"] < MIN_WORDS) | (100 * got["n_repeat_words"] > MAX_REPEATED * got["n_words"])
            langs = _langs(b.column(lang)) if lang >= 0 else [""] * b.num_rows
            llr = scores(Words(b.column(text), lower=True), langs, model)
            more = [*(pa.array(v.astype(np.int64)) for v in got.values()), pa.array(failed), pa.array(llr), pa.array(~failed & (llr >= model.threshold))]
            yield pa.RecordBatch.from_arrays([*b.columns, *more], [*names, *new])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return docs.mapInArrow(run, f"{kinds}, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, base_failed boolean, llr double, kept boolean")
