"""BPE training (exact, batched, sampled), encoding of distinct pieces, fingerprint and packing."""

from __future__ import annotations

import hashlib
import heapq
import uuid
from collections import Counter, defaultdict
from collections.abc import Iterable, Sequence
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import ArrayType, IntegerType

from ..functions.views import bucket
from ..tables import cleaned, shared_folder

BASE = 256
LIMIT = 1 << 16


@dataclass(frozen=True)
class Merges:
    """Ordered merges over byte ids; merge i makes id 256 + i."""

    pairs: tuple[tuple[int, int], ...] = field(default=())

    @property
    def size(self) -> int:
        return BASE + len(self.pairs)

    @cached_property
    def ranks(self) -> dict[tuple[int, int], int]:
        return {p: i for i, p in enumerate(self.pairs)}

    @cached_property
    def strings(self) -> list[bytes]:
        out = [bytes([i]) for i in range(BASE)]
        for a, b in self.pairs:
            out.append(out[a] + out[b])
        return out

    def fingerprint(self) -> str:
        """Changes with any merge or their order; shards are pinned to it."""
        return hashlib.sha256(repr(self.pairs).encode()).hexdigest()[:16]

    def to_df(self, spark: SparkSession) -> DataFrame:
        rows = [(i, self.strings[a], self.strings[b], BASE + i) for i, (a, b) in enumerate(self.pairs)]
        return spark.createDataFrame(rows, "rank int, left binary, right binary, id int")

    def encode(self, piece: bytes) -> list[int]:
        """Joins the pair of the lowest rank, everywhere it stands, until no known pair is left."""
        ids = list(piece)
        while len(ids) > 1:
            rank, pair = min(((self.ranks.get(p, len(self.pairs)), p) for p in zip(ids, ids[1:])))
            if rank == len(self.pairs):
                break
            ids = _join(ids, pair, BASE + rank)
        return ids

    def decode(self, ids: Iterable[int]) -> bytes:
        return b"".join(self.strings[i] for i in ids)


def _join(ids: list[int], pair: tuple[int, int], new: int) -> list[int]:
    out, i = [], 0
    while i < len(ids):
        if i + 1 < len(ids) and (ids[i], ids[i + 1]) == pair:
            out.append(new)
            i += 2
        else:
            out.append(ids[i])
            i += 1
    return out


def train_on(pieces: dict[bytes, float], merges: int, least: float = 1.0) -> Merges:
    """Exact training on weighted pieces: the heaviest pair, ties to the smallest ids; an index of pairs to pieces keeps rounds cheap."""
    words = [(list(p), w) for p, w in sorted(pieces.items()) if len(p) > 1 and w > 0]
    weight: Counter = Counter()
    where: dict[tuple[int, int], set[int]] = defaultdict(set)
    for i, (ids, w) in enumerate(words):
        for p in zip(ids, ids[1:]):
            weight[p] += w
            where[p].add(i)
    heap = [(-w, p) for p, w in weight.items()]
    heapq.heapify(heap)
    done: list[tuple[int, int]] = []
    while heap and len(done) < merges:
        w, pair = heapq.heappop(heap)
        if -w != weight.get(pair, 0):
            continue
        if -w < least:
            break
        new = BASE + len(done)
        done.append(pair)
        touched = set()
        for i in where.pop(pair):
            ids, n = words[i]
            for p in zip(ids, ids[1:]):
                weight[p] -= n
                touched.add(p)
            ids = _join(ids, pair, new)
            words[i] = (ids, n)
            for p in zip(ids, ids[1:]):
                weight[p] += n
                where[p].add(i)
                touched.add(p)
        weight.pop(pair, None)
        for p in touched:
            if weight.get(p, 0) > 1e-9 and p != pair:
                heapq.heappush(heap, (-weight[p], p))
    return Merges(tuple(done))


def train_bpe(hist: DataFrame, vocab_size: int, mode: str = "exact", *, head: int = 200_000, pairs_per_round: int = 64, fraction: float = 0.1) -> Merges:
    """Merges from ``hist(piece, cnt)``.

    ``exact`` trains on all pieces: on the driver while there are ``head`` distinct ones at most, else as ``batched`` does, with the same
    merges; ``sampled`` does so with an md5 share of all pieces; ``batched`` leaves all pieces in the cluster and begins with the ``pairs_per_round`` heaviest pairs.
    """
    if vocab_size > LIMIT:
        raise ValueError("ids must fit 16 bits")
    if mode == "batched":
        shared_folder(hist.sparkSession)
        return _train_batched(hist.checkpoint(), vocab_size - BASE, pairs_per_round)
    if mode == "sampled":
        hist = hist.where(bucket("bpe", F.col("piece")) < int(fraction * 2**32))
    shared_folder(hist.sparkSession)
    hist = hist.checkpoint()
    if hist.count() > head:
        return _train_batched(hist, vocab_size - BASE, pairs_per_round)
    rows = hist.where("cnt > 0").select(F.col("piece").cast("binary"), F.col("cnt").cast("long")).toArrow().combine_chunks()
    return Merges(tuple(_train_flat(Flat.read(rows.column("piece"), rows.column("cnt").to_numpy()), vocab_size - BASE)))


class Flat:
    """Pieces laid end to end as ids with links to their neighbours, so that a merge costs a look at the places where its pair can stand.

    A merged neighbour's place becomes -2, places outside of pieces are -1.
    """

    def __init__(self, pieces: list[bytes], weights: np.ndarray | None = None):
        self._lay(np.frombuffer(b"".join(pieces), np.uint8), np.fromiter(map(len, pieces), np.int64, len(pieces)), weights)

    @classmethod
    def read(cls, column: pa.Array | pa.ChunkedArray, weights: np.ndarray | None = None, width: int = 1) -> Flat:
        """Pieces of a column of strings or bytes; ids take ``width`` bytes each."""
        column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
        flat, raw = object.__new__(cls), column.cast(pa.large_binary())
        bounds = np.frombuffer(raw.buffers()[1], np.int64)[raw.offset : raw.offset + len(raw) + 1] if len(raw) else np.zeros(1, np.int64)
        data = np.frombuffer(raw.buffers()[2] or b"", np.uint8)[bounds[0] : bounds[-1]]
        flat._lay(data if width == 1 else data.view("<u2"), np.diff(bounds) // width, weights)
        return flat

    def _lay(self, data: np.ndarray, sizes: np.ndarray, weights: np.ndarray | None) -> None:
        self.starts = np.cumsum(sizes + 1) - sizes
        self.ids = np.full(len(data) + len(sizes) + 1, -1, np.int32)
        inside = np.ones(len(self.ids), bool)
        inside[0] = inside[self.starts + sizes] = False
        self.ids[inside] = data
        self.next, self.before = np.arange(1, len(self.ids) + 1, dtype=np.int32), np.arange(-1, len(self.ids) - 1, dtype=np.int32)
        self.next[-1] = self.before[0] = 0
        self.sizes = sizes
        self.weights = None if weights is None else np.repeat(weights, sizes + 1)

    def pairs(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Those of the places where a pair begins, and the pairs' keys."""
        a, b = self.ids[at], self.ids[self.next[at]]
        good = (a >= 0) & (b >= 0)
        return at[good], a[good].astype(np.int64) << 32 | b[good]

    def grouped(self, at: np.ndarray) -> tuple[list[int], list[int], list[np.ndarray]]:
        """Pairs that begin at these places: keys, weights, and the places of each in their order."""
        at, keys = self.pairs(at)
        if not len(at):
            return [], [], []
        order = np.argsort(keys, kind="stable")
        keys, at = keys[order], at[order]
        first = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
        return keys[first].tolist(), np.add.reduceat(self.weights[at - 1], first).tolist(), np.split(at, first[1:])

    def standing(self, at: np.ndarray, pair: tuple[int, int]) -> np.ndarray:
        """Those of the places, in their order, where the pair is to be joined from the left."""
        at = at[self.ids[at] == pair[0]]
        at = at[self.ids[self.next[at]] == pair[1]]
        if pair[0] == pair[1] and len(at):  # of a run each second one
            first = np.r_[True, self.before[at[1:]] != at[:-1]]
            run = np.flatnonzero(first)
            at = at[(np.arange(len(at)) - np.repeat(run, np.diff(np.r_[run, len(at)]))) % 2 == 0]
        return at

    def join(self, at: np.ndarray, new: int) -> None:
        gone = self.next[at]
        after = self.next[gone]
        self.ids[at], self.ids[gone] = new, -2
        self.next[at], self.before[after] = after, at

    def merge(self, pair: tuple[int, int], new: int, told: bool = False) -> tuple[np.ndarray, np.ndarray] | None:
        """Joins the pair, from the left, everywhere; ``told`` gives the changes of pairs' weights."""
        at = self.standing(np.flatnonzero(self.ids == pair[0]), pair)
        if told:
            lost, gone = self.pairs(np.unique(np.r_[self.before[at], at, self.next[at]]))
        self.join(at, new)
        if not told:
            return None
        made, come = self.pairs(np.unique(np.r_[self.before[at], at]))
        return _summed(np.r_[gone, come], np.r_[-self.weights[lost - 1], self.weights[made - 1]])

    def merge_all(self, pairs: Sequence[tuple[int, int]], first: int) -> None:
        """Joins the pairs in turn to ``first`` and the ids after it. A pair's places are all known once the later of its two ids is made."""
        if not len(pairs):
            return
        keys = np.array([a << 32 | b for a, b in pairs], np.int64)
        rank = np.argsort(keys)
        keys = keys[rank]
        left, right = (np.zeros(first + len(pairs) + 2, bool) for _ in "ab")
        left[[a for a, _ in pairs]] = right[[b for _, b in pairs]] = True
        places: dict[int, np.ndarray] = {}

        def look(at: np.ndarray) -> None:
            at = at[left[self.ids[at]]]
            at = at[right[self.ids[self.next[at]]]]
            at, found = self.pairs(at)
            i = np.minimum(np.searchsorted(keys, found), len(keys) - 1)
            hit = keys[i] == found
            at, i = at[hit], rank[i[hit]]
            if len(at):
                order = np.argsort(i, kind="stable")
                at, i = at[order], i[order]
                cut = np.flatnonzero(np.r_[True, i[1:] != i[:-1]])
                places.update(zip(i[cut].tolist(), np.split(at, cut[1:])))

        look(np.arange(len(self.ids), dtype=np.int32))
        for i, pair in enumerate(pairs):
            if i not in places:
                continue
            at = self.standing(places.pop(i), pair)
            self.join(at, first + i)
            if left[first + i] or right[first + i]:
                look(np.unique(np.r_[self.before[at], at]))

    def counts(self) -> np.ndarray:
        """Ids of each piece."""
        kept = np.cumsum(self.ids >= 0)
        return kept[self.starts + self.sizes] - kept[self.starts - 1]


def _summed(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each key once, with the sum of its values."""
    if not len(keys):
        return keys, values
    order = np.argsort(keys)
    keys, values = keys[order], values[order]
    first = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
    return keys[first], np.add.reduceat(values, first)


def _train_flat(flat: Flat, merges: int, first: int = BASE, least: int = 1) -> list[tuple[int, int]]:
    """The merges of ``train_on`` while the heaviest pair weighs ``least``; each looks at its own places and their neighbours alone."""
    keys, n, at = flat.grouped(np.arange(len(flat.ids), dtype=np.int32))
    weight, places = dict(zip(keys, n)), dict(zip(keys, at))
    heap = [(-n, p) for p, n in weight.items()]
    heapq.heapify(heap)
    done: list[tuple[int, int]] = []
    while heap and len(done) < merges:
        n, key = heapq.heappop(heap)
        if weight.get(key) != -n:
            continue
        if -n < least:
            break
        pair, new = (key >> 32, key & 0xFFFFFFFF), first + len(done)
        done.append(pair)
        at = flat.standing(places[key], pair)
        lost, less, _ = flat.grouped(np.unique(np.r_[flat.before[at], at, flat.next[at]]))
        flat.join(at, new)
        for p, x in zip(lost, less):
            if left := weight[p] - x:
                weight[p] = left
                if left >= least:
                    heapq.heappush(heap, (-left, p))
            else:
                del weight[p], places[p]
        for p, x, found in zip(*flat.grouped(np.unique(np.r_[flat.before[at], at]))):
            if x >= least:
                weight[p], places[p] = x, found
                heapq.heappush(heap, (-x, p))
            else:
                weight[p], places[p] = x, found[:0]
    return done


def _binary(ids: np.ndarray, sizes: np.ndarray) -> pa.Array:
    """Ids of pieces that lie end to end, each piece as 16-bit integers."""
    bounds = np.r_[0, np.cumsum(sizes)] * 2
    return pa.Array.from_buffers(pa.large_binary(), len(sizes), [None, pa.py_buffer(bounds.astype(np.int64)), pa.py_buffer(ids.astype("<u2"))]).cast(pa.binary())


_ROWS = "ids binary, cnt bigint, pair array<bigint>, n array<bigint>"


def _merged(pairs: list[tuple[int, int]], first: int, width: int):
    """For the pieces of a task: what of them has more than one id after the merges, then rows with the weights of the pairs in that."""

    def run(batches):
        lists, seen, held = pa.list_(pa.int64()), [], 0
        names = ["ids", "cnt", "pair", "n"]
        for batch in batches:
            if not batch.num_rows:
                continue
            n = batch.column(1).to_numpy()
            flat = Flat.read(batch.column(0), n, width)
            flat.merge_all(pairs, first)
            at, keys = flat.pairs(np.arange(len(flat.ids), dtype=np.int32))
            seen.append(_summed(keys, flat.weights[at - 1]))
            held += len(seen[-1][0])
            if held > 1_000_000:
                seen = [_summed(*(np.concatenate(x) for x in zip(*seen)))]
                held = len(seen[0][0]) // 2
            sizes = flat.counts()
            long = sizes > 1
            ids = flat.ids[flat.ids >= 0][np.repeat(long, sizes)]
            none = pa.nulls(int(long.sum()), lists)
            yield pa.RecordBatch.from_arrays([_binary(ids, sizes[long]), pa.array(n[long], pa.int64()), none, none], names)
        if seen:
            keys, n = _summed(*(np.concatenate(x) for x in zip(*seen)))
            for i in range(0, len(keys), 65_536):
                yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.binary()), pa.nulls(1, pa.int64()), *(pa.array([x[i : i + 65_536]], lists) for x in (keys, n))], names)

    return run


def _runs(heavy: list[int]):
    """For the pieces of a task: their runs of ids that follow one another in pairs of these keys, each with its weight."""
    keys = np.sort(np.array(heavy, np.int64))

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            flat = Flat.read(batch.column(0), batch.column(1).to_numpy(), 2)
            at, found = flat.pairs(np.arange(len(flat.ids), dtype=np.int32))
            at = at[keys[np.minimum(np.searchsorted(keys, found), len(keys) - 1)] == found]
            tied, go = np.zeros(len(flat.ids), bool), np.zeros(len(flat.ids), bool)
            tied[at] = go[at] = go[at + 1] = True
            go = np.flatnonzero(go)
            first = np.flatnonzero(~tied[go - 1])
            if len(first):
                rows = pa.table({"ids": _binary(flat.ids[go], np.diff(np.r_[first, len(go)])), "cnt": flat.weights[go[first] - 1]})
                yield from rows.group_by("ids").aggregate([("cnt", "sum")]).rename_columns(["ids", "cnt"]).to_batches()

    return run


def _train_batched(hist: DataFrame, merges: int, k: int, guide: int = 2_000_000) -> Merges:
    """The merges of ``train_on`` with all pieces in the cluster.

    A pair's weight never grows, and ids that will be joined stand in a pair that weighs as much already. So the merges down to a weight are
    those of the runs of ids in pairs of at least that weight. A round takes the ``k`` heaviest pairs of all, collects these runs with their
    summed weights, trains on them down to the lightest of the pairs, and joins what it found in all pieces. ``k`` follows the runs' size:
    fewer pairs where all runs hold over ``guide`` ids (one pair is always taken), more where they hold far less.
    """
    spark = hist.sparkSession
    pieces, width, folder = hist.where("cnt > 0 and octet_length(piece) > 1").select(F.col("piece").cast("binary").alias("ids"), F.col("cnt").cast("long").alias("cnt")), 1, None
    done: list[tuple[int, int]] = []
    new: list[tuple[int, int]] = []
    k = max(1, k)
    try:
        while len(done) < merges:
            last, folder = folder, _folder(spark)
            pieces.mapInArrow(_merged(new, BASE + len(done) - len(new), width), _ROWS).write.parquet(f"{folder}/pieces")
            _drop(spark, last)
            rows, width = spark.read.schema(_ROWS).parquet(f"{folder}/pieces"), 2
            pieces = rows.where("ids is not null").select("ids", "cnt")
            pairs = rows.where("pair is not null").select(F.explode(F.arrays_zip("pair", "n")).alias("x")).groupBy("x.pair").agg(F.sum("x.n").alias("n"))
            while True:
                top = pairs.orderBy(F.desc("n"), "pair").limit(k + 1).collect()
                if not top:
                    return Merges(tuple(done))
                least = top[k].n + 1 if len(top) > k else 1
                if least > top[0].n:  # more than k heaviest ones
                    least = top[0].n
                    top = pairs.where(F.col("n") == least).collect()
                path = f"{folder}/runs-{k}"
                with cleaned(spark):
                    pieces.mapInArrow(_runs([r.pair for r in top if r.n >= least]), "ids binary, cnt bigint").groupBy("ids").agg(F.sum("cnt").alias("cnt")).write.parquet(path)
                runs = spark.read.schema("ids binary, cnt bigint").parquet(path)
                size = runs.agg(F.sum(F.octet_length("ids"))).first()[0] // 2
                if size <= guide or k == 1:
                    break
                k = max(1, k // 4)
            found = runs.toArrow()
            new = _train_flat(Flat.read(found.column("ids"), found.column("cnt").to_numpy(), 2), merges - len(done), BASE + len(done), least)
            done += new
            k *= 4 if size * 8 <= guide else 2 if size * 2 <= guide else 1
    finally:
        _drop(spark, folder)
    return Merges(tuple(done))


def _folder(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/bpe-{uuid.uuid4().hex}"


def _drop(spark: SparkSession, folder: str | None) -> None:
    if folder:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def token_count(merges: Merges):
    """A column function: number of tokens of a piece. Joining pairs in order of rank in all pieces of a batch gives what ``encode`` gives for each."""

    @pandas_udf("bigint")
    def count(piece: pd.Series) -> pd.Series:
        flat = Flat([(p or "").encode() for p in piece])
        flat.merge_all(merges.pairs, BASE)
        return pd.Series(flat.counts())

    return count


def encode(text: Column, merges: Merges, rule) -> Column:
    """Ids of a text: its pieces encoded one by one, distinct pieces of a batch once."""
    from ..functions.pretokenize import pretokenize

    @pandas_udf("array<int>")
    def ids(pieces: pd.Series) -> pd.Series:
        known: dict[str, list[int]] = {}
        return pieces.map(lambda ps: None if ps is None else [i for p in ps for i in (known[p] if p in known else known.setdefault(p, merges.encode(p.encode())))])

    return ids(pretokenize(text, rule))


def decode(ids: Column, merges: Merges) -> Column:
    @pandas_udf("string")
    def text(column: pd.Series) -> pd.Series:
        return column.map(lambda x: None if x is None else merges.decode(x).decode(errors="replace"))

    return text(ids)


def fertility(df: DataFrame, merges: Merges, rule, by: list[str], text: str = "text", hist: DataFrame | None = None) -> DataFrame:
    """Tokens, words and bytes by group; each group's distinct piece is encoded once and weighted by its count (``hist``, if it is there already)."""
    from ..functions.pretokenize import n_words, piece_histogram

    hist = piece_histogram(df, rule, by, text) if hist is None else hist
    tokens = hist.groupBy(*by).agg(F.sum(F.col("cnt") * token_count(merges)("piece")).alias("tokens"), F.sum("cnt").alias("pieces"))
    sizes = df.groupBy(*by).agg(F.sum(n_words(F.col(text))).alias("words"), F.sum(F.octet_length(text)).cast("long").alias("bytes"))
    out = tokens.join(sizes, by)
    return out.withColumns({"fertility": F.round(F.col("tokens") / F.col("words"), 6), "bytes_per_token": F.round(F.col("bytes") / F.col("tokens"), 6)})


def mixture_sweep(df: DataFrame, sides: Column, shares: list[float], rules: list[str], vocab_size: int, *, text: str = "text", head: int = 200_000) -> DataFrame:
    """Fertility of the lower-resource side when a tokenizer is trained at each share of it, under each rule.

    ``sides`` is true for that side. One histogram of chunks by side serves both rules, one of pieces by side and rule all shares: a mixture only
    weights its counts (in whole 10^-15 of the mixture). ``head`` is as in ``train_bpe``; floor and fertility are summed up in the cluster.
    Output: rule, share, merges, fertility, floor, slack (fertility / floor - 1).
    """
    from ..functions.pretokenize import chunk_histogram, n_words, piece_histogram

    shared_folder(df.sparkSession)
    with cleaned(df.sparkSession):
        chunks = chunk_histogram(df.withColumn("_lrl", sides), ["_lrl"], text).checkpoint()
    words = chunks.where("_lrl").agg(F.sum(F.col("cnt") * n_words(F.col("chunk")))).first()[0] or 0
    rows = []
    for rule in rules:
        hist = piece_histogram(chunks, rule, ["_lrl"], "chunk", "cnt").checkpoint()
        totals = {r["_lrl"]: max(1, r["n"]) for r in hist.groupBy("_lrl").agg(F.sum("cnt").alias("n")).collect()}
        own = hist.where("_lrl")
        floor = (own.where(~F.col("piece").rlike(r"^\s+$")).agg(F.sum("cnt")).first()[0] or 0) / max(words, 1)
        for share in shares:
            w = F.when(F.col("_lrl"), F.lit(share / totals.get(True, 1))).otherwise(F.lit((1 - share) / totals.get(False, 1)))
            mixed = hist.groupBy("piece").agg(F.round(F.sum(w * F.col("cnt")) * 1e15).cast("long").alias("cnt")).where("cnt > 0")
            merges = train_bpe(mixed, vocab_size, head=head)
            tokens = own.agg(F.sum(F.col("cnt") * token_count(merges)("piece"))).first()[0] or 0
            rows.append((rule, float(share), len(merges.pairs), tokens / max(words, 1), floor, tokens / max(words, 1) / floor - 1 if floor else 0.0))
    return df.sparkSession.createDataFrame(rows, "rule string, share double, merges int, fertility double, floor double, slack double")


def check_uint16(ids: DataFrame, column: str = "ids") -> DataFrame:
    """Rows with an id that 16 bits can't hold."""
    return ids.where(F.exists(column, lambda x: (x < 0) | (x >= LIMIT)))


def to_u16(ids: Column) -> Column:
    """Little-endian 16-bit integers, natively."""
    return F.unhex(F.concat_ws("", F.transform(ids, lambda x: F.lpad(F.hex((x % 256 * 256 + F.shiftright(x, 8)).cast("int")), 4, "0"))))


@pandas_udf(ArrayType(IntegerType()))
def from_u16(data: pd.Series) -> pd.Series:
    return data.map(lambda x: None if x is None else np.frombuffer(x, "<u2").astype("int32"))


def require_fingerprint(shards: DataFrame, fingerprint: str) -> DataFrame:
    """The shards; a row packed with another tokenizer ends the query."""
    wrong = F.col("fingerprint") != F.lit(fingerprint)
    return shards.withColumn("fingerprint", F.when(wrong, F.raise_error(F.concat(F.lit("packed with tokenizer "), F.col("fingerprint")))).otherwise(F.col("fingerprint")))


def pack(docs: DataFrame, ctx: int = 4096, *, shards: int = 8, end: int = 0, key: str = "doc_id", ids: str = "ids") -> DataFrame:
    """``shard``, ``seq`` and ``ids`` of at most ``ctx``: documents follow one another, an end id after each, inside shards dealt by md5 of the key.

    One shuffle into shards; sums run inside a shard. Tokens are kept one for one; a shard's last sequence may be short.
    """
    ended = docs.select(F.col(key).alias("k"), F.concat(F.col(ids), F.array(F.lit(end))).alias("x"), F.pmod(bucket("shard", F.col(key)), F.lit(shards)).cast("int").alias("shard"))
    run = Window.partitionBy("shard").orderBy("k")
    placed = ended.withColumn("at", F.sum(F.size("x")).over(run.rowsBetween(Window.unboundedPreceding, 0)) - F.size("x"))
    first, last = F.floor(F.col("at") / ctx), F.floor((F.col("at") + F.size("x") - 1) / ctx)
    cut = placed.select("shard", "k", "at", "x", F.explode(F.sequence(first, last)).alias("seq"))
    begin = F.greatest(F.col("seq") * ctx - F.col("at"), F.lit(0))
    stop = F.least((F.col("seq") + 1) * ctx - F.col("at"), F.size("x").cast("long"))
    part = cut.select("shard", "seq", F.struct((F.col("at") + begin).alias("at"), F.slice("x", (begin + 1).cast("int"), (stop - begin).cast("int")).alias("x")).alias("p"))
    return part.groupBy("shard", "seq").agg(F.flatten(F.transform(F.sort_array(F.collect_list("p")), lambda p: p["x"])).alias("ids"))
