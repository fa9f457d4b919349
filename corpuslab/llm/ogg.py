"""Ogg pages: checksums, lacing, logical streams and granule positions.

A payload is cut into packets of ``FRAME`` 8-bit samples that are dealt in turn to ``STREAMS`` logical
streams of one physical stream. A page's granule position is the number of samples of the whole
recording up to the end of the last packet that ends on the page; the reader derives each packet's
time from it and rebuilds the payload in time order.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices, utf8

RATE, FRAME, STREAMS, UNIT = 8000, 960, 2, 192
_HEAD = struct.Struct("<4sBBqIIIB")
_INTRO = struct.Struct("<8sIIHHQ")
_MAGIC = b"pcm-u8\x00\x01"
_NONE = -1
_MIRROR = bytes(int(f"{b:08b}"[::-1], 2) for b in range(256))


def page_crc(page: bytes) -> int:
    """Ogg's CRC-32 (polynomial 04C11DB7, most significant bit first, no inversion), by the mirrored one of zlib."""
    return int(f"{zlib.crc32(page.translate(_MIRROR), 0xFFFFFFFF) ^ 0xFFFFFFFF:032b}"[::-1], 2)


def _page(flags: int, granule: int, serial: int, number: int, lacing: bytes, body: bytes) -> bytes:
    raw = _HEAD.pack(b"OggS", 0, flags, granule, serial, number, 0, len(lacing)) + lacing + body
    return raw[:22] + page_crc(raw).to_bytes(4, "little") + raw[26:]


def paginate(packets: list[tuple[bytes, int]], serial: int) -> list[tuple[int, bytes]]:
    """(granule, page) of one logical stream; the first packet has a page of its own, and packets may span pages."""
    cut: list[tuple[int, int, bytes, bytes]] = []
    lacing, body, granule, going_on = bytearray(), [], _NONE, False

    def flush(goes_on: bool) -> None:
        nonlocal lacing, body, granule, going_on
        cut.append((1 if going_on else 0, granule, bytes(lacing), b"".join(body)))
        lacing, body, granule, going_on = bytearray(), [], _NONE, goes_on

    for n, (packet, end) in enumerate(packets):
        values, at, k = b"\xff" * (len(packet) // 255) + bytes([len(packet) % 255]), 0, 0
        while k < len(values):
            part = values[k : k + 255 - len(lacing)]
            lacing += part
            k += len(part)
            upto = at + sum(part)
            body.append(packet[at:upto])
            at = upto
            if k == len(values):
                granule = end
            if len(lacing) == 255 and (k < len(values) or n + 1 < len(packets)):
                flush(k < len(values))
        if n == 0 and len(packets) > 1:
            flush(False)
    flush(False)
    return [(g, _page(f | (2 if i == 0 else 0) | (4 if i == len(cut) - 1 else 0), g, serial, i, lace, b)) for i, (f, g, lace, b) in enumerate(cut)]


def mux(payload: bytes) -> bytes:
    """The physical stream of a payload. Serial numbers follow from the payload, so equal payloads give equal bytes."""
    base, frames = zlib.crc32(payload), [payload[i : i + FRAME] for i in range(0, len(payload), FRAME)]
    streams = []
    for s in range(STREAMS):
        packets = [(_INTRO.pack(_MAGIC, RATE, FRAME, s, STREAMS, len(payload)), 0)]
        packets += [(frames[k], min((k + 1) * FRAME, len(payload))) for k in range(s, len(frames), STREAMS)]
        streams.append(paginate(packets, (base + s) & 0xFFFFFFFF))
    first = [x[0][1] for x in streams]
    rest, last = [], 0
    for s, pages in enumerate(streams):  # a page without an end of packet stays behind the one before it
        last = 0
        for i, (g, page) in enumerate(pages[1:]):
            last = max(last, g)
            rest.append((last, s, i, page))
    return b"".join(first + [x[3] for x in sorted(rest, key=lambda x: x[:3])])


class OggError(ValueError):
    pass


def read_pages(data: bytes) -> Iterator[tuple[int, int, int, int, bytes, bytes]]:
    """(flags, granule, serial, number, lacing, body) of each page whose checksum holds; else raises OggError."""
    at = 0
    while at < len(data):
        if data[at : at + 4] != b"OggS" or at + 27 > len(data):
            raise OggError(f"no page at byte {at}")
        _, version, flags, granule, serial, number, crc, n = _HEAD.unpack_from(data, at)
        lacing = data[at + 27 : at + 27 + n]
        end = at + 27 + n + sum(lacing)
        if version or len(lacing) < n or end > len(data):
            raise OggError(f"broken page at byte {at}")
        if page_crc(data[at : at + 22] + b"\0\0\0\0" + data[at + 26 : end]) != crc:
            raise OggError(f"wrong checksum at byte {at}")
        yield flags, granule, serial, number, lacing, data[at + 27 + n : end]
        at = end


def demux(data: bytes) -> dict[int, dict]:
    """By serial number: ``packets`` as (start sample, bytes), the header's fields, and the number of pages.

    Starts derive from granule positions: the last packet that ends on a page ends at the page's
    granule, and each earlier packet of the page ends one turn of all streams before its successor.
    """
    out: dict[int, dict] = {}
    for flags, granule, serial, number, lacing, body in read_pages(data):
        if flags & 2:
            if serial in out:
                raise OggError("serial number used twice")
            out[serial] = {"pages": 0, "packets": [], "open": b"", "intro": None, "ended": False}
        x = out.get(serial)
        if x is None or x["ended"] or number != x["pages"]:
            raise OggError("page lost or out of order")
        if bool(flags & 1) != bool(x["open"]):
            raise OggError("packet continued wrongly")
        x["pages"] += 1
        x["ended"] = bool(flags & 4)
        done, at, begun, part = [], 0, 0, x["open"]
        for v in lacing:
            at += v
            if v < 255:
                done.append(part + body[begun:at])
                begun, part = at, b""
        x["open"] = part + body[begun:at]
        if x["intro"] is None and done:
            magic, rate, frame, index, streams, total = _INTRO.unpack(done.pop(0))
            if magic != _MAGIC:
                raise OggError("unknown mapping")
            x["intro"] = {"rate": rate, "frame": frame, "index": index, "streams": streams, "total": total}
        if done:
            end, turn = granule, x["intro"]["frame"] * x["intro"]["streams"]
            starts = [end - len(done[-1])]
            for _ in done[-2::-1]:
                starts.append((starts[-1] // x["intro"]["frame"]) * x["intro"]["frame"] - turn)
            x["packets"] += zip(reversed(starts), done)
    if any(x["open"] or not x["ended"] for x in out.values()):
        raise OggError("stream ends inside a packet")
    return out


def rebuild(streams: dict[int, dict]) -> bytes:
    """The payload: all streams' packets in the order of their times, which must leave no gap."""
    packets = sorted((p for x in streams.values() for p in x["packets"]), key=lambda p: p[0])
    at = 0
    for start, body in packets:
        if start != at:
            raise OggError(f"gap at sample {at}")
        at += len(body)
    if any(x["intro"]["total"] != at for x in streams.values()):
        raise OggError("samples are missing")
    return b"".join(p[1] for p in packets)


def features(streams: dict[int, dict], payload: bytes) -> str:
    """Duration, counts and level of the samples, in fixed format."""
    a = np.frombuffer(payload, np.uint8).astype(np.int32) - 128
    rate = next(iter(streams.values()))["intro"]["rate"]
    crossings = int(np.count_nonzero((a[1:] < 0) != (a[:-1] < 0)))
    return (
        f"streams={len(streams)};pages={sum(x['pages'] for x in streams.values())};packets={sum(len(x['packets']) for x in streams.values())};"
        f"ms={len(a) * 1000 // rate};mean={a.sum() / len(a):.4f};rms={np.sqrt(float(np.dot(a, a)) / len(a)):.4f};crossings={crossings}"
    )


def pad(raw: bytes) -> bytes:
    """``raw`` with spaces up to the next positive multiple of ``UNIT`` bytes."""
    return raw + b" " * (max(1, -(-len(raw) // UNIT)) * UNIT - len(raw))


def store(df: DataFrame, *, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key``, ``n_bytes`` and ``media``: each text's padded UTF-8 bytes as samples of an Ogg stream.

    Null text counts as empty. One row for each row, whatever the key; other columns are left behind.
    """

    def run(batches):
        for b in slices(batches, 1):
            raw = utf8(b.column(1)).to_pylist()
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(map(len, raw), pa.int64()), pa.array([mux(pad(x)) for x in raw], pa.binary())], ["key", "n_bytes", "media"])

    df = df.select(F.col(key), F.col(text))
    return df.mapInArrow(run, f"`{key}` {df.schema[0].dataType.simpleString()}, n_bytes bigint, media binary")


def read(df: DataFrame, *, key: str = "doc_id", media: str = "media", keep: tuple[str, ...] = ()) -> DataFrame:
    """``key``, ``keep``, ``media``, ``payload``, ``feature`` and ``error`` of each stored stream.

    A stream that is null or broken gives null payload and feature and says why in ``error``.
    """
    df = df.select(F.col(key), *keep, F.col(media).alias("media"))
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)
    names = [f.name for f in df.schema]

    def one(data: bytes | None):
        try:
            if data is None:
                raise OggError("no stream")
            streams = demux(data)
            payload = rebuild(streams)
            return payload, features(streams, payload), None
        except (OggError, struct.error, StopIteration) as e:
            return None, None, str(e) or type(e).__name__

    def run(batches):
        for b in batches:
            out = [one(x) for x in b.column(b.num_columns - 1).to_pylist()]
            more = [pa.array([x[i] for x in out], t) for i, t in enumerate((pa.binary(), pa.string(), pa.string()))]
            yield pa.RecordBatch.from_arrays([*b.columns, *more], [*names, "payload", "feature", "error"])

    return df.mapInArrow(run, f"{kinds}, payload binary, feature string, error string")


def digest(df: DataFrame) -> DataFrame:
    """Stores every text, reads it back and describes both forms.

    Null text counts as empty and has a payload of padding alone; texts of any length are stored whole; equal texts give equal values and
    repeated rows are answered each. An empty table gives an empty one; other columns are left behind, whatever their names.
    """
    return read(store(df), keep=("n_bytes",)).select(
        "doc_id",
        "n_bytes",
        F.octet_length("payload").cast("long").alias("payload_bytes"),
        F.sha2("payload", 256).alias("payload_sha256"),
        F.crc32(F.expr("substring(payload, -16, 16)")).alias("tail_crc32"),
        F.octet_length("media").cast("long").alias("media_bytes"),
        F.sha2("media", 256).alias("media_sha256"),
        "feature",
        "error",
    )
