"""Shared helpers: table reading, Arrow batch slicing, shared scratch folders."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from ..tables import shared_folder

#: Bytes that separate words: 0x20 and 0x09-0x0D, which is also what ``bytes.split()`` takes.
SPACES = b" \t\n\x0b\x0c\r"
#: Texts handled at once inside a Python worker, in bytes; one text is never cut.
SLICE_BYTES = 3_000_000
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@lru_cache(maxsize=8)
def _session_folder(spark: SparkSession, base: str) -> str:
    """One folder for all scratch tables of an application, removed when its driver ends."""
    context = spark.sparkContext
    folder = f"{base}/corpuslab-{context.applicationId}"
    path = context._jvm.org.apache.hadoop.fs.Path(folder)
    files = path.getFileSystem(context._jsc.hadoopConfiguration())
    files.mkdirs(path)
    files.deleteOnExit(path)
    return folder


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder that driver and executors share; it lies in the cluster's checkpoint folder and goes when the driver ends."""
    return f"{_session_folder(spark, shared_folder(spark))}/{name}-{uuid.uuid4().hex}"


#: Spark drops a query's shuffle files at its end where this is set, not when the driver happens to collect garbage.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def store(df: DataFrame, path: str, **options) -> DataFrame:
    """``df`` as a table in the shared folder, read back: computed once, safe from lost executors, and its shuffle files are gone."""
    spark = df.sparkSession
    before = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")
    try:
        df.write.options(**options).parquet(path)
    finally:
        spark.conf.set(_CLEANUP, before)
    return spark.read.schema(df.schema).parquet(path)


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Gives the context the session's checkpoint folder, if it has none yet."""
    shared_folder(spark)


def utf8(column: pa.Array) -> pa.Array:
    """A string column as bytes; null becomes empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.fill_null("").cast(pa.large_binary())


def slices(batches: Iterator[pa.RecordBatch], text: int, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """The same rows in batches whose texts sum to about ``limit`` bytes at most, one row at least."""
    for batch in batches:
        if not batch.num_rows:
            continue
        size = np.diff(np.asarray(utf8(batch.column(text)).buffers()[1]).view("<i8")[: batch.num_rows + 1])
        part = np.cumsum(size) // limit
        cuts = [0, *(np.flatnonzero(np.diff(part)) + 1), batch.num_rows]
        for a, b in zip(cuts, cuts[1:]):
            if b > a:
                yield batch.slice(a, b - a)


class Words:
    """The words of a slice of texts: ``codes`` index ``distinct``; ``starts`` bounds each text's words."""

    def __init__(self, texts: pa.Array, lower: bool = False):
        import pyarrow.compute as pc

        raw = utf8(texts)
        bounds = np.asarray(raw.buffers()[1]).view("<i8")[raw.offset : raw.offset + len(raw) + 1]
        data = np.frombuffer(raw.buffers()[2] or b"", np.uint8)[bounds[0] : bounds[-1]]
        if lower:  # by a table: pyarrow's own ascii_lower goes wrong on slices
            data = _LOWER[data]
        strings = pa.Array.from_buffers(pa.large_string(), len(raw), [None, pa.py_buffer((bounds - bounds[0]).astype("<i8")), pa.py_buffer(np.ascontiguousarray(data))])
        lists = pc.ascii_split_whitespace(strings)
        flat, offsets = lists.values, np.asarray(lists.offsets, dtype=np.int64)
        flat, offsets = flat.slice(offsets[0], offsets[-1] - offsets[0]), offsets - offsets[0]
        full = np.asarray(pc.binary_length(flat)) > 0
        if not full.all():  # white space at an edge gives an empty word
            offsets = np.concatenate([[0], np.cumsum(full)])[offsets]
            flat = flat.filter(pa.array(full))
        coded = flat.dictionary_encode()
        self.starts = offsets
        self.codes = np.asarray(coded.indices, dtype=np.int64)
        self.distinct = coded.dictionary.cast(pa.large_binary()).to_numpy(zero_copy_only=False).tolist()
        self.counts = np.diff(offsets)

    def owner(self) -> np.ndarray:
        """For each word, the row of its text."""
        return np.repeat(np.arange(len(self.counts)), self.counts)

    def hashes(self) -> np.ndarray:
        """A 64-bit hash for each word."""
        import xxhash

        one = xxhash.xxh3_64_intdigest
        table = np.fromiter((one(w) for w in self.distinct), np.uint64, len(self.distinct))
        return table[self.codes] if len(table) else np.zeros(0, np.uint64)


def mix(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Hash of an ordered pair of 64-bit hashes (a finaliser of the splitmix kind)."""
    with np.errstate(over="ignore"):
        z = a * np.uint64(0x9E3779B97F4A7C15) + b
        z ^= z >> np.uint64(31)
        z *= np.uint64(0xBF58476D1CE4E5B9)
        z ^= z >> np.uint64(29)
        z *= np.uint64(0x94D049BB133111EB)
        return z ^ (z >> np.uint64(32))


def row_sums(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Sum of ``values`` between consecutive ``starts``; empty spans give 0."""
    total = np.concatenate([np.zeros(1, values.dtype if values.dtype.kind == "f" else np.int64), np.cumsum(values)])
    return total[starts[1:]] - total[starts[:-1]]
