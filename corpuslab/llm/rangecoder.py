"""Adaptive context-mixing range coder for token ids, in blocks that are reset and checked on their own.

A block's ids are coded by ``lanes`` range coders side by side, each over a contiguous part, in lockstep: a step
codes one id of every lane with numpy, and then the model, which all lanes of the block share, learns the
step's ids. Order 2 and order 1 each predict one id from the ids before it, with a confidence; mixing weights
learnt for each pair of confidences give the probabilities that order 2 is right, that order 1 is, or that
neither is; then the id itself is coded by adaptive order-0 frequencies. The reader repeats every step of the model.

A block: magic, sizes, checksum of all that follows, keys and lengths of its documents, the lanes' lengths,
the lanes' digits of 16 bits.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np

STEPS = 96
#: Bits of the whole that a mixing context's three shares make up.
MIX = 14
MAGIC = b"CMRC\x02"
_HEAD = struct.Struct("<5sIIQII")
_LOW, _MASK, _U16 = np.uint64(1) << np.uint64(32), (np.uint64(1) << np.uint64(48)) - np.uint64(1), np.uint64(16)
_TOP = np.uint64(32)
_MOST, _GAIN = 1 << 22, 24


class BlockError(ValueError):
    pass


class _Model:
    """State of a block. An entry of orders 1 and 2 is the id it predicts, times 8, plus a confidence of 0 to 7."""

    def __init__(self, alphabet: int, n: int):
        self.alphabet = alphabet
        self.counts, self.sum = np.ones(alphabet, np.int64), alphabet
        self.size = 1 << max(10, min(20, (2 * n).bit_length()))
        nothing = np.int32(alphabet << 3)
        self.one, self.two = np.full(alphabet + 1, nothing), np.full(self.size, nothing)
        self.mixed = np.tile(np.array([64, 8, 8], np.int64), (128, 1))
        self._sums()

    def _sums(self) -> None:
        """Cumulated order-0 counts, and the shares of each mixing context out of 1 << MIX."""
        self.cum = np.zeros(self.alphabet + 1, np.uint64)
        np.cumsum(self.counts.view(np.uint64), out=self.cum[1:])
        self.total = np.uint64(self.sum)
        share = 1 + self.mixed * ((1 << MIX) - 3) // self.mixed.sum(axis=1, keepdims=True)
        share[:, 0] += (1 << MIX) - share.sum(axis=1)
        self.widths = share.astype(np.uint64).ravel()
        self.edges = (np.cumsum(share, axis=1) - share).astype(np.uint64).ravel()

    def predict(self, before: np.ndarray, before2: np.ndarray):
        """Slots of order 2, the entries and ids of orders 1 and 2, and the mixing context of each lane, times 3."""
        slot = (((before2 * 0x1E3779B1) ^ before) * 0x5EBCA6B >> 12) & (self.size - 1)
        e1, e2 = self.one.take(before), self.two.take(slot)
        one, two = e1 >> 3, e2 >> 3
        context = ((e2 & 7) << 4) | ((e1 & 7) << 1) | (one == two)
        return slot, e1, e2, one, two, context * 3

    def learn(self, ids: np.ndarray, ids32: np.ndarray, before: np.ndarray, slot: np.ndarray, e1, e2, right1, right2, cell: np.ndarray) -> None:
        fresh = (ids32 << 3) | 1
        for table, at, e, right in ((self.one, before, e1, right1), (self.two, slot, e2, right2)):
            sure = e & 7
            table[at] = np.where(right, e + (sure < 7), np.where(sure <= 1, fresh, e - 2))
        self.counts += _GAIN * np.bincount(ids, minlength=self.alphabet)
        self.sum += _GAIN * len(ids)
        if self.sum > _MOST:
            self.counts = (self.counts + 1) >> 1
            self.sum = int(self.counts.sum())
        self.mixed += 16 * np.bincount(cell, minlength=384).reshape(128, 3)
        full = self.mixed.sum(axis=1) > 1 << 16
        self.mixed[full] = (self.mixed[full] + 1) >> 1
        self._sums()

    def find(self, aim: np.ndarray) -> np.ndarray:
        """The id whose cumulated counts hold each value; looked up in ascending order, which is kinder to the cache."""
        order = np.sort((aim << np.uint64(32)) | np.arange(len(aim), dtype=np.uint64))
        out = np.empty(len(aim), np.int64)
        out[(order & np.uint64(0xFFFFFFFF)).astype(np.int64)] = np.searchsorted(self.cum, order >> np.uint64(32), side="right") - 1
        return out


class _Writer:
    def __init__(self, lanes: int, steps: int):
        self.low, self.range = np.zeros(lanes, np.uint64), np.full(lanes, _MASK + np.uint64(1), np.uint64)
        self.digits, self.at = np.zeros((4 * steps + 4, lanes), np.uint32), np.zeros(lanes, np.int64)

    def put(self, lane: slice | np.ndarray, part: np.ndarray, start: np.ndarray, width: np.ndarray) -> None:
        """Narrows the lanes (the first ones, as a slice, or those of an index) to ``width`` parts from ``start`` on; all unsigned 64-bit."""
        low, size = self.low[lane] + part * start, part * width
        over = np.flatnonzero(low > _MASK)
        if over.size:
            who = over if isinstance(lane, slice) else lane[over]
            self.digits[self.at[who] - 1, who] += 1
            low &= _MASK
        short = np.flatnonzero(size < _LOW)
        while short.size:
            who = short if isinstance(lane, slice) else lane[short]
            rest, at = low[short], self.at[who]
            self.digits[at, who] = (rest >> _TOP).astype(np.uint32)
            self.at[who] = at + 1
            low[short] = (rest << _U16) & _MASK
            wider = size[short] << _U16
            size[short] = wider
            short = short[wider < _LOW]
        self.low[lane], self.range[lane] = low, size

    def end(self) -> tuple[np.ndarray, np.ndarray]:
        """Lengths of the lanes in digits, and all digits in lane order. One last digit settles each lane."""
        who = np.arange(len(self.at))
        self.digits[self.at, who] = ((self.low >> _TOP) + np.uint64(1)).astype(np.uint32)
        self.at += 1
        most = int(self.at.max())
        for k in range(most - 1, 0, -1):  # carries run to the front
            self.digits[k - 1] += self.digits[k] >> 16
        used = np.arange(most) < self.at[:, None]
        return self.at, np.ascontiguousarray(self.digits[:most].T.astype("<u2"))[used]


class _Reader:
    def __init__(self, lengths: np.ndarray, digits: np.ndarray):
        self.ends = np.cumsum(lengths)
        self.at = self.ends - lengths
        self.digits = np.concatenate([digits.astype(np.uint64), np.zeros(1, np.uint64)])
        self.gap, self.range = np.zeros(len(lengths), np.uint64), np.full(len(lengths), _MASK + np.uint64(1), np.uint64)
        for _ in range(3):
            self.gap = self.gap << _U16 | self._next(np.arange(len(lengths)))

    def _next(self, lane: np.ndarray) -> np.ndarray:
        at = self.at[lane]
        self.at[lane] = at + 1
        return self.digits.take(np.where(at < self.ends[lane], at, len(self.digits) - 1))

    def take(self, lane: slice | np.ndarray, part: np.ndarray, start: np.ndarray, width: np.ndarray) -> None:
        gap, size = self.gap[lane] - part * start, part * width
        short = np.flatnonzero(size < _LOW)
        while short.size:
            gap[short] = gap[short] << _U16 | self._next(short if isinstance(lane, slice) else lane[short])
            wider = size[short] << _U16
            size[short] = wider
            short = short[wider < _LOW]
        self.gap[lane], self.range[lane] = gap, size


def _lanes(n: int) -> tuple[int, int]:
    lanes = max(1, -(-n // STEPS))
    return lanes, -(-n // lanes)


def pack_ids(ids: np.ndarray, alphabet: int) -> bytes:
    """The coded ids alone: lane lengths and digits."""
    n = len(ids)
    lanes, steps = _lanes(n)
    lanes = -(-n // steps) if n else 0
    if not n:
        return b""
    grid = np.zeros(lanes * steps, np.int64)
    grid[:n] = ids
    grid = grid.reshape(lanes, steps).T.copy()
    model, out = _Model(alphabet, n), _Writer(lanes, steps)
    before = before2 = np.full(lanes, alphabet, np.int64)
    for t in range(steps):
        k = lanes if (lanes - 1) * steps + t < n else lanes - 1
        before, before2 = before[:k], before2[:k]  # the last lane may have ended
        now = grid[t, :k]
        now32 = now.astype(np.int32)
        slot, e1, e2, one, two, cell = model.predict(before, before2)
        right1, right2 = one == now32, two == now32
        cell += np.where(right2, 1, right1 * np.int32(2))
        neither = ~(right1 | right2)
        lane = slice(0, k)
        out.put(lane, out.range[lane] >> np.uint64(MIX), model.edges.take(cell), model.widths.take(cell))
        missed = np.flatnonzero(neither)
        if missed.size:
            x = now[missed]
            out.put(missed, out.range[missed] // model.total, model.cum.take(x), model.counts.view(np.uint64).take(x))
        model.learn(now, now32, before, slot, e1, e2, right1, right2, cell)
        before2, before = before, now
    lengths, digits = out.end()
    return lengths.astype("<u4").tobytes() + digits.tobytes()


def unpack_ids(data: bytes, n: int, alphabet: int) -> np.ndarray:
    if not n:
        return np.zeros(0, np.int64)
    lanes, steps = _lanes(n)
    lanes = -(-n // steps)
    lengths = np.frombuffer(data, "<u4", lanes).astype(np.int64)
    reader, model = _Reader(lengths, np.frombuffer(data, "<u2", int(lengths.sum()), 4 * lanes)), _Model(alphabet, n)
    grid = np.zeros((steps, lanes), np.int64)
    before = before2 = np.full(lanes, alphabet, np.int64)
    for t in range(steps):
        k = lanes if (lanes - 1) * steps + t < n else lanes - 1
        before, before2, lane = before[:k], before2[:k], slice(0, k)
        slot, e1, e2, one, two, cell = model.predict(before, before2)
        part = reader.range[lane] >> np.uint64(MIX)
        aim = reader.gap[lane] // part
        kind = (aim >= model.edges.take(cell + 1)).astype(np.int32) + (aim >= model.edges.take(cell + 2))
        cell += kind
        reader.take(lane, part, model.edges.take(cell), model.widths.take(cell))
        now = np.where(kind == 1, two, one).astype(np.int64)
        missed = np.flatnonzero(kind == 0)
        if missed.size:
            part = reader.range[missed] // model.total
            x = model.find(np.minimum(reader.gap[missed] // part, model.total - np.uint64(1)))
            reader.take(missed, part, model.cum.take(x), model.counts.view(np.uint64).take(x))
            now[missed] = x
        grid[t, :k] = now
        now32 = now.astype(np.int32)
        model.learn(now, now32, before, slot, e1, e2, one == now32, two == now32, cell)
        before2, before = before, now
    return grid.T.reshape(-1)[:n]


def pack_block(keys: list[int | None], lengths: list[int], ids: np.ndarray, alphabet: int) -> bytes:
    """A block of whole documents: ``lengths[i]`` ids belong to ``keys[i]``; keys are 64-bit integers or null."""
    if len(ids) and not 0 <= int(ids.min()) <= int(ids.max()) < alphabet:
        raise BlockError("id outside the alphabet")
    null = np.array([k is None for k in keys], bool)
    body = np.array([k or 0 for k in keys], "<i8").tobytes() + np.packbits(null).tobytes() + np.array(lengths, "<u4").tobytes() + pack_ids(ids, alphabet)
    return _HEAD.pack(MAGIC, alphabet, len(keys), len(ids), zlib.crc32(body), zlib.crc32(np.asarray(ids, "<u4").tobytes())) + body


def unpack_block(data: bytes) -> tuple[list[int | None], list[int], np.ndarray]:
    """Keys, lengths and ids of a block; a block that was changed raises BlockError."""
    if len(data) < _HEAD.size:
        raise BlockError("block too short")
    magic, alphabet, docs, n, crc, ids_crc = _HEAD.unpack_from(data)
    body = data[_HEAD.size :]
    if magic != MAGIC or zlib.crc32(body) != crc:
        raise BlockError("wrong checksum of a block")
    a, b = 8 * docs, 8 * docs + -(-docs // 8)
    null = np.unpackbits(np.frombuffer(body[a:b], np.uint8))[:docs].astype(bool)
    keys = [None if x else k for k, x in zip(np.frombuffer(body[:a], "<i8").tolist(), null.tolist())]
    lengths = np.frombuffer(body[b : b + 4 * docs], "<u4").tolist()
    ids = unpack_ids(body[b + 4 * docs :], n, alphabet)
    if zlib.crc32(ids.astype("<u4").tobytes()) != ids_crc or sum(lengths) != n:
        raise BlockError("wrong checksum of ids")
    return keys, lengths, ids
