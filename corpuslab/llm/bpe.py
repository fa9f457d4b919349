"""Byte-level BPE: a priority queue of merge ranks over a doubly linked list of symbols.

The vocabulary file is a parameter and stays where it is. Texts are cut at single spaces between
visible characters, where no pre-token can cross; each distinct chunk is encoded once per worker.
"""

from __future__ import annotations

import json
import struct
from collections.abc import Iterator
from functools import lru_cache
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices

#: The white space of Unicode's White_Space property.
_WS = r"\t-\r \x85\xa0  -     　"
#: The published pre-token classes of byte-level BPE.
_PIECES = rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{_WS}\p{{L}}\p{{N}}]+|[{_WS}]+(?![^{_WS}])|[{_WS}]+"
#: Entries that a worker remembers; beyond it starts anew, which costs time only.
MEMORY = 300_000
#: Marks that make a pre-token of their own after a word.
_MARKS = frozenset(".,;:!?)")


def byte_letters() -> dict[int, str]:
    """The printable stand-in of each byte in a byte-level vocabulary: visible Latin-1 stays, the rest moves up."""
    stay = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    moved = [b for b in range(256) if b not in set(stay)]
    return {b: chr(b) for b in stay} | {b: chr(256 + i) for i, b in enumerate(moved)}


def _pack(ids: list[int]) -> bytes:
    """Little-endian unsigned 32-bit integers."""
    return struct.pack(f"<{len(ids)}I", *ids)


class _Uneven(Exception):
    """A chunk that borders on white space: the text needs the careful cut."""


class Bpe:
    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab, letters = spec["model"]["vocab"], byte_letters()
        back = {c: b for b, c in letters.items()}
        self.special = {x["content"]: x["id"] for x in spec["added_tokens"]}
        self.strings: list[bytes] = [b""] * (1 + max([*vocab.values(), *self.special.values()]))
        for token, i in vocab.items():
            self.strings[i] = bytes(back[c] for c in token) if all(c in back for c in token) else token.encode()
        for token, i in self.special.items():
            self.strings[i] = token.encode()
        self.byte_ids = [vocab[letters[b]] for b in range(256)]
        self.rank: dict[int, int] = {}
        self.made: list[int] = []
        for r, pair in enumerate(spec["model"]["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            self.rank[vocab[a] << 20 | vocab[b]] = r
            self.made.append(vocab[a + b])
        self._find = regex.compile(_PIECES).findall
        self._cut = regex.compile(rf"(?<=[^{_WS}]) (?=[^{_WS}])").split
        self._edge = regex.compile(rf"\A(?![{_WS}]).*(?<![{_WS}])\Z", regex.S).match
        self._spaced = any(c.isspace() for x in self.special for c in x)
        self._heads = {x[0] for x in self.special if x}
        self._split = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")").split if self.special else None
        self._pieces: dict[str, bytes] = {}
        self._inner = _Chunks(self, " ")
        self._first = _Chunks(self, "")

    def merge(self, piece: bytes) -> list[int]:
        """Ids of one pre-token: the pair of lowest rank, leftmost first, is joined until none is left."""
        ids, rank, made = [self.byte_ids[b] for b in piece], self.rank, self.made
        n = len(ids)
        if n == 1:
            return ids
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        queue = []
        for i in range(n - 1):
            if (r := rank.get(ids[i] << 20 | ids[i + 1])) is not None:
                queue.append(r << 40 | i)
        heapify(queue)
        while queue:
            top = heappop(queue)
            r, i = top >> 40, top & 0xFFFFFFFFFF
            if (a := ids[i]) < 0 or (j := after[i]) >= n or rank.get(a << 20 | ids[j]) != r:
                continue  # stale: one of its symbols has been joined since
            ids[i], ids[j] = made[r], -1
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                if (s := rank.get(ids[i] << 20 | ids[k])) is not None:
                    heappush(queue, s << 40 | i)
            if (p := before[i]) >= 0 and (s := rank.get(ids[p] << 20 | ids[i])) is not None:
                heappush(queue, s << 40 | p)
        return [x for x in ids if x >= 0]

    def _plain(self, text: str) -> bytes:
        memory, out = self._pieces, []
        for piece in self._find(text):
            ids = memory.get(piece)
            if ids is None:
                ids = _pack(self.merge(piece.encode()))
                if len(piece) < 64:
                    if len(memory) >= MEMORY:
                        memory.clear()
                    memory[piece] = ids
            out.append(ids)
        return b"".join(out)

    def chunk(self, text: str) -> bytes:
        """Ids of a stretch of text that starts and ends where a pre-token may; special tokens are cut out first."""
        if not self._split or not any(c in text for c in self._heads):
            return self._plain(text)
        return b"".join(_pack([self.special[x]]) if x in self.special else self._plain(x) for x in self._split(text) if x)

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        if not text:
            return b""
        if self._spaced:
            return self.chunk(text)
        try:
            head, *rest = text.split(" ")
            return b"".join([self._first[head], *map(self._inner.__getitem__, rest)])
        except _Uneven:
            head, *rest = self._cut(text)
            return b"".join([self.chunk(head), *(self._inner[x] if self._edge(x) else self.chunk(" " + x) for x in rest)])

    def decode(self, ids: bytes) -> bytes:
        """The vocabulary strings joined, as valid UTF-8 (broken sequences give U+FFFD)."""
        joined = b"".join(map(self.strings.__getitem__, np.frombuffer(ids, "<u4").tolist()))
        try:
            joined.decode()
            return joined
        except UnicodeDecodeError:
            return joined.decode(errors="replace").encode()


class _Chunks(dict):
    """Remembers the ids of chunks that stand after a space (or, with no lead, at a text's start)."""

    def __init__(self, owner: Bpe, lead: str):
        self.owner, self.lead = owner, lead

    def __missing__(self, chunk: str) -> bytes:
        if any(c in chunk for c in self.owner._heads):
            if not self.owner._edge(chunk):
                raise _Uneven
            ids = self.owner.chunk(self.lead + chunk)
        elif chunk.isalpha():  # one pre-token
            ids = _pack(self.owner.merge((self.lead + chunk).encode()))
        elif chunk[:-1].isalpha() and chunk[-1] in _MARKS:  # a word and a mark: two
            ids = self[chunk[:-1]] + self.owner.chunk(chunk[-1])
        elif not self.owner._edge(chunk) or not chunk:
            raise _Uneven
        else:
            ids = self.owner.chunk(self.lead + chunk)
        if len(chunk) < 64:
            if len(self) >= MEMORY:
                self.clear()
            self[chunk] = ids
        return ids


@lru_cache(maxsize=4)
def load(path: str) -> Bpe:
    """One coder for each vocabulary file and worker."""
    return Bpe(path)


def encode(df: DataFrame, vocab_path: str, *, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key`` and ``ids`` (binary, little-endian unsigned 32-bit) of each row; null text counts as empty.

    Rows are kept one to one, repeated and null keys too; other columns are left behind.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = load(vocab_path)
        for b in slices(batches, 1):
            ids = [coder.encode(x or "") for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ids, pa.binary())], ["key", "ids"])

    return _run(df.select(F.col(key), F.col(text)), run, key, "ids binary")


def decode(df: DataFrame, vocab_path: str, *, key: str = "doc_id", ids: str = "ids") -> DataFrame:
    """``key`` and ``decoded`` (string) of each row of ids; null ids count as none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = load(vocab_path)
        for b in batches:
            out = pa.array([coder.decode(x or b"") for x in b.column(1).to_pylist()], pa.binary()).cast(pa.string())
            yield pa.RecordBatch.from_arrays([b.column(0), out], ["key", "decoded"])

    return _run(df.select(F.col(key), F.col(ids)), run, key, "decoded string")


def round_trip(df: DataFrame, vocab_path: str, *, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key``, ``ids`` and ``decoded`` in one pass of a single worker: encode, then decode those ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = load(vocab_path)
        for b in slices(batches, 1):
            ids = [coder.encode(x or "") for x in b.column(1).to_pylist()]
            out = pa.array([coder.decode(x) for x in ids], pa.binary()).cast(pa.string())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ids, pa.binary()), out], ["key", "ids", "decoded"])

    return _run(df.select(F.col(key), F.col(text)), run, key, "ids binary, decoded string")


def _run(df: DataFrame, run, key: str, more: str) -> DataFrame:
    kind = df.schema[0].dataType.simpleString()
    return df.mapInArrow(run, f"`{key}` {kind}, {more}")


def digest(df: DataFrame, vocab_path: str) -> DataFrame:
    """Per document: number of ids and the digests of ids and of the decoded text.

    Null text counts as empty and has no ids; texts of any length are coded whole; repeated rows are answered each; an empty table gives
    an empty one; other columns are left behind, whatever their names.
    """
    done = round_trip(df, vocab_path)
    return done.select(
        "doc_id",
        F.expr("cast(octet_length(ids) div 4 as bigint)").alias("n_tokens"),
        F.sha2("ids", 256).alias("ids_sha256"),
        F.sha2(F.encode("decoded", "UTF-8"), 256).alias("decoded_sha256"),
    )
