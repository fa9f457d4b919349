"""Token ids as files: texts are encoded by a public tokenizer, written in key order, and read back.

The writer deals documents to parts by quantiles of their key, sorts each part, and cuts it into blocks of whole
documents, each coded by the range coder on its own. A file holds blocks, with their part and number, so
any reader can open a block alone; part and block in order give all ids in ascending key order.
"""

from __future__ import annotations

import json
import os
import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Words, scratch, slices, store
from .rangecoder import pack_block, unpack_block

#: Ids that a block is closed at; a document is never cut.
BLOCK_IDS = 1 << 21
#: Stored bytes of a table for each part that is sorted and coded by one task.
PART_BYTES, MOST_PARTS = 64 << 20, 200_000
END_ID = 2
SCHEMA = "part int, block bigint, ids bigint, data binary"
#: Pre-tokens that a worker remembers the ids of; beyond it starts anew, which costs time only.
MEMORY = 1_200_000
#: Text encoded at once, in bytes.
ENCODE_SLICE = 6_000_000
#: Fixed value: the pre-token pattern of a lower-case vocabulary with word ends that drops white space.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: Classes of characters: separator, letter, digit, other visible one, and those that leave a word to the library.
_GAP, _LETTER, _DIGIT, _OTHER, _HARD = range(5)


def _character_tables(special: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Class and lower case of the code points up to U+20FF; the last entry stands for all above.

    Sure are those with one lower case that composition leaves alone. An apostrophe may start a contraction and a
    special token's first character a special token: words with them are left to the library.
    """
    kind, low = np.full(0x2101, _HARD, np.uint8), np.arange(0x2101, dtype="<u4")
    for c in [*range(0x21, 0x7F), *range(0xA1, 0x180), 0x2013, 0x2014, *range(0x2018, 0x201F), 0x2026, 0x20AC]:
        name, lower = unicodedata.category(chr(c)), chr(c).lower()
        if name in ("Cf", "No", "Nl") or len(lower) != 1 or unicodedata.normalize("NFC", lower) != lower:
            continue
        kind[c] = _LETTER if name[0] == "L" else _DIGIT if name == "Nd" else _OTHER
        low[c] = ord(lower)
    kind[[ord("'"), *(ord(x[0]) for x in special if ord(x[0]) < 0x2100)]] = _HARD
    kind[10] = _GAP
    return kind, low


class WordCoder:
    """Encodes texts word by word with the tokenizers library.

    Good for tokenizers that drop white space: no token crosses it, so a text's ids are those of its words in order,
    and each distinct word is encoded once. With the pre-token pattern known, words are cut into lower-case
    pre-tokens, which are fewer and are remembered, and the library encodes many in one call: the last id of each is one with a word end.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.alphabet = self.tokenizer.get_vocab_size()
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        special = [x["content"] for x in spec["added_tokens"]]
        self.inner = None
        suffix = spec["model"].get("end_of_word_suffix")
        rules = (spec["pre_tokenizer"] or {}).get("pretokenizers", [])
        if suffix and [r["type"] for r in rules] == ["Split", "ByteLevel"] and rules[0]["pattern"] == {"Regex": PATTERN} and rules[0]["invert"]:
            spec["normalizer"], spec["added_tokens"], spec["truncation"], spec["padding"] = None, [], None, None
            spec["pre_tokenizer"]["pretokenizers"][0] = {"type": "WhitespaceSplit"}
            self.inner = Tokenizer.from_str(json.dumps(spec))
            self.is_end = np.zeros(self.alphabet, bool)
            self.is_end[[i for t, i in spec["model"]["vocab"].items() if t.endswith(suffix)]] = True
        self.kind, self.low = _character_tables(special)
        if self.inner is None:
            self.kind[:10] = self.kind[11:] = _HARD
        self._forget()

    def _forget(self) -> None:
        """Remembered pre-tokens (strings) and words (bytes), by number; their ids lie in one table."""
        self.known: dict[str | bytes, int] = {}
        self.table, self.first, self.size = np.zeros(0, "<u4"), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def _remember(self, keys: list[str] | list[bytes], ids: np.ndarray, size: np.ndarray) -> None:
        self.known.update(zip(keys, range(len(self.known), len(self.known) + len(keys))))
        self.first = np.concatenate([self.first, len(self.table) + np.cumsum(size) - size])
        self.size, self.table = np.concatenate([self.size, size]), np.concatenate([self.table, ids])

    def _whole(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """All ids of the texts by the tokenizer as it is, and the number of each."""
        found = [e.ids for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
        return np.array([i for x in found for i in x], "<u4"), np.fromiter(map(len, found), np.int64, len(found))

    def _learn(self, pieces: list[str], words: list[bytes]) -> None:
        for i in range(0, len(pieces), 25_600):
            part = pieces[i : i + 25_600]
            found = self.inner.encode_batch_fast([" ".join(part[k : k + 256]) for k in range(0, len(part), 256)], add_special_tokens=False)
            ids = np.concatenate([np.array(e.ids, "<u4") for e in found])
            ends = np.flatnonzero(self.is_end[ids]) + 1
            if len(ends) == len(part):
                self._remember(part, ids, np.diff(ends, prepend=0))
            else:  # a symbol outside the vocabulary
                self._remember(part, *self._whole(part))
        for i in range(0, len(words), 20_000):
            part = words[i : i + 20_000]
            self._remember(part, *self._whole([w.decode() for w in part]))

    def _cut(self, words: list[bytes]) -> tuple[list[str | bytes], np.ndarray]:
        """What each word is made of, in order: lower-case pre-tokens, or the word itself; and the word's number for each."""
        points = np.frombuffer(b"\n".join(words).decode().encode("utf-32-le"), "<u4")
        at = np.minimum(points, 0x2100)
        kind, text = self.kind[at], self.low[at]
        gap = kind == _GAP
        word = np.cumsum(gap)
        hard = np.unique(word[kind == _HARD])
        if len(hard):
            is_hard = np.zeros(len(words), bool)
            is_hard[hard] = True
            kind[is_hard[word] & ~gap] = _GAP
        new = np.flatnonzero((kind != _GAP) & ((kind == _DIGIT) | (kind != np.concatenate([[_GAP], kind[:-1]]))))
        over = np.flatnonzero((kind != _GAP) & ((kind == _DIGIT) | (kind != np.concatenate([kind[1:], [_GAP]])))) + 1
        told, text = word[new], text.tobytes().decode("utf-32-le", "replace")
        pieces: list[str | bytes] = [text[a:b] for a, b in zip(new.tolist(), over.tolist())]
        if not len(hard):
            return pieces, told
        pieces += [words[i] for i in hard.tolist()]
        told = np.concatenate([told, hard])
        order = np.argsort(told, kind="stable")
        return [pieces[i] for i in order.tolist()], told[order]

    def _ids_of(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """All ids of distinct words in order, and the number of each word's."""
        if not words:
            return np.zeros(0, "<u4"), np.zeros(0, np.int64)
        pieces, word = self._cut(words)
        found = list(map(self.known.get, pieces))
        missing = {p for p, n in zip(pieces, found) if n is None}
        if missing and len(self.known) + len(missing) > MEMORY:
            self._forget()
            missing, found = set(pieces), [None] * len(pieces)
        self._learn([p for p in missing if type(p) is str], [p for p in missing if type(p) is bytes])
        number = np.array([self.known[p] if n is None else n for p, n in zip(pieces, found)] if missing else found, np.int64)
        size = self.size[number]
        total = np.bincount(word, size, minlength=len(words)).astype(np.int64)
        return self.table[np.repeat(self.first[number] - np.cumsum(size) + size, size) + np.arange(int(size.sum()))], total

    def encode(self, texts: pa.Array, end: int = END_ID) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in order, an end id after each, and the number of ids of each text."""
        words = Words(texts)
        table, size = self._ids_of(words.distinct)
        first, counts = np.cumsum(size) - size, size[words.codes]
        upto = np.concatenate([[0], np.cumsum(counts)])
        n = np.diff(upto[words.starts]) + 1
        ends = np.cumsum(n) - 1
        out = np.empty(int(upto[-1]) + len(n), "<u4")
        inner = np.ones(len(out), bool)
        inner[ends] = False
        out[ends] = end
        out[inner] = table[np.arange(int(upto[-1])) + np.repeat(first[words.codes] - upto[:-1], counts)]
        return out, n


@lru_cache(maxsize=2)
def coder(path: str) -> WordCoder:
    return WordCoder(path)


def _bounds(docs: DataFrame, parts: int) -> list[int]:
    """Keys that cut the table into about equal parts; a sketch of bounded size over the key column alone."""
    if parts < 2:
        return []
    found = docs.select("doc_id").stat.approxQuantile("doc_id", [i / parts for i in range(1, parts)], min(0.01, 0.1 / parts))
    return sorted({int(x) for x in found})


def _parts(docs: DataFrame) -> int:
    """Shuffle partitions of the session, or more where Spark's estimate of the table's bytes, from its files, asks for it."""
    size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    wanted = -(-size // PART_BYTES) if size < 1 << 50 else 0  # rows that come from no file are of unknown size
    return max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(wanted, MOST_PARTS))


def write(docs: DataFrame, path: str, vocab_path: str, *, end: int = END_ID, block_ids: int = BLOCK_IDS, parts: int | None = None) -> None:
    """Writes the ids of all ``docs(doc_id long, text)`` to ``path``: rows of ``part``, ``block``, ``ids`` (their number) and ``data``.

    Order is by doc_id, null first, then by a hash of the text; null text counts as empty. Repeated rows are
    all written. Sorting spills; a worker holds one block.
    """
    bounds = _bounds(docs, parts or _parts(docs))

    def tokens(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cuts = np.array(bounds, np.int64)
        for b in slices(batches, 1, ENCODE_SLICE):
            ids, n = coder(vocab_path).encode(b.column(1), end)
            kind = "<u2" if coder(vocab_path).alphabet <= 1 << 16 else "<u4"
            width = np.dtype(kind).itemsize
            offsets = np.concatenate([[0], np.cumsum(n)]) * width
            data = pa.Array.from_buffers(pa.large_binary(), len(n), [None, pa.py_buffer(offsets.astype("<i8")), pa.py_buffer(ids.astype(kind))])
            key = b.column(0)
            part = np.where(np.asarray(key.is_null()), 0, np.searchsorted(cuts, np.asarray(key.fill_null(0)), side="right"))
            yield pa.RecordBatch.from_arrays([key, b.column(2), pa.array(part.astype(np.int32)), data.cast(pa.binary())], ["doc_id", "h", "part", "ids"])

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        alphabet = coder(vocab_path).alphabet
        kind = "<u2" if alphabet <= 1 << 16 else "<u4"
        part, number, keys, lengths, held, total = -1, 0, [], [], [], 0

        def close() -> pa.RecordBatch:
            ids = np.frombuffer(b"".join(held), kind).astype(np.int64)
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([number], pa.int64()), pa.array([total], pa.int64()), pa.array([pack_block(keys, lengths, ids, alphabet)], pa.binary())], ["part", "block", "ids", "data"])

        for b in batches:
            for key, p, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                raw = data.as_py()
                n = len(raw) // np.dtype(kind).itemsize
                if keys and (p != part or total + n > block_ids):
                    yield close()
                    number, keys, lengths, held, total = number + 1 if p == part else 0, [], [], [], 0
                elif p != part:
                    number = 0
                part, total = p, total + n
                keys.append(key)
                lengths.append(n)
                held.append(raw)
        if keys:
            yield close()

    coded = docs.select(F.col("doc_id").cast("long"), "text", F.xxhash64("text")).mapInArrow(tokens, "doc_id bigint, h bigint, part int, ids binary")
    dealt = coded.repartitionById(len(bounds) + 1, "part").sortWithinPartitions("part", F.col("doc_id").asc_nulls_first(), "h").select("doc_id", "part", "ids")
    store(dealt.mapInArrow(blocks, "part int, block bigint, ids bigint, data binary"), path, compression="none")


def read(spark: SparkSession, path: str) -> DataFrame:
    """``part``, ``block``, ``doc_id``, ``inside`` (ids of the block before it) and ``ids`` (binary, little-endian unsigned 32-bit) of every document in the files.

    Every block's checksums are verified; a changed one ends the query with an error.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for part, block, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                keys, lengths, ids = unpack_block(data.as_py())
                ends = np.cumsum([0, *lengths])
                raw = ids.astype("<u4")
                for i in range(0, len(keys), 500):
                    j = min(i + 500, len(keys))
                    texts = pa.Array.from_buffers(pa.large_binary(), j - i, [None, pa.py_buffer((4 * (ends[i : j + 1] - ends[i])).astype("<i8")), pa.py_buffer(raw[ends[i] : ends[j]].tobytes())])
                    yield pa.RecordBatch.from_arrays([pa.array([part] * (j - i), pa.int32()), pa.array([block] * (j - i), pa.int64()), pa.array(keys[i:j], pa.int64()), pa.array(ends[i:j]), texts.cast(pa.binary())], ["part", "block", "doc_id", "inside", "ids"])

    files = spark.read.schema(SCHEMA).parquet(path)
    return files.select("part", "block", "data").mapInArrow(run, "part int, block bigint, doc_id bigint, inside bigint, ids binary")


def block_starts(spark: SparkSession, path: str) -> DataFrame:
    """``part``, ``block`` and ``begin``: ids of all blocks before it. Sums run inside parts; one row for each part is summed over all."""
    sizes = spark.read.schema(SCHEMA).parquet(path).select("part", "block", "ids")
    inside = sizes.withColumn("_in", F.sum("ids").over(Window.partitionBy("part").orderBy("block")) - F.col("ids"))
    whole = sizes.groupBy("part").agg(F.sum("ids").alias("n"))
    whole = whole.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("_parts"))
    return inside.join(whole, "part").select("part", "block", (F.col("_in") + F.col("_parts")).alias("begin"))


def digest(docs: DataFrame, vocab_path: str) -> DataFrame:
    """Writes all ids, reads the files back and gives each document's place, number of ids and checksum.

    Null and empty texts have the end id alone; a document longer than a block is a block of its own; repeated rows and null ids (which
    come first) are written each. An empty table gives an empty one; other columns are left behind, whatever their names.
    """
    spark, path = docs.sparkSession, scratch(docs.sparkSession, "token-files")
    write(docs, path, vocab_path)
    told = read(spark, path).select("part", "block", "doc_id", "inside", F.expr("cast(octet_length(ids) div 4 as bigint)").alias("n_tokens"), F.crc32("ids").alias("ids_crc32"))
    placed = told.join(block_starts(spark, path), ["part", "block"])
    return placed.select("doc_id", (F.col("begin") + F.col("inside")).alias("start"), "n_tokens", "ids_crc32")
