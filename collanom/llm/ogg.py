"""Media columns in Ogg: texts stored as sampled streams, with checksums, lacing and granule positions.

A payload is cut into packets of a fixed number of 8-bit samples and multiplexed with a second logical
stream that holds a description. The reader verifies every page's checksum and sequence number,
reassembles packets from the lacing values (across pages too), separates the logical streams by serial
number and derives the time of each packet from the granule positions.

Defined results: a null text is an empty payload; every payload is padded with spaces to a positive
multiple of the frame; equal texts, repeated rows too, give equal bytes; an empty table gives no rows; a
long text is one stream of as many packets as it needs; other columns are ignored, whatever their names.
A damaged page raises `OggError`.
"""

from __future__ import annotations

import hashlib
import json
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame

from .common import per_row

FRAME = 192
RATE = 8000
#: Samples of a packet; a multiple of the frame. Packets of more than a page run over several pages.
PACKET = FRAME * 500
#: Fixed values of the container: capture pattern, header flags, lacing values of a page.
MAGIC, CONTINUED, FIRST, LAST, MOST_LACES = b"OggS", 1, 2, 4, 255
_HEADER = struct.Struct("<4sBBqIIIB")
_REVERSED = bytes(int(f"{b:08b}"[::-1], 2) for b in range(256))
_HEAD = struct.Struct("<8sBIHQ")


class OggError(ValueError):
    """A page or stream that does not hold together."""


def page_crc(page: bytes) -> int:
    """The container's checksum (polynomial 0x04C11DB7, no reflection, zero start), by way of zlib's reflected one."""
    x = zlib.crc32(page.translate(_REVERSED), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(x.to_bytes(4, "little").translate(_REVERSED), "big")


@dataclass
class _Writer:
    """One logical stream: packets become pages of at most 255 lacing values."""

    serial: int
    sequence: int = 0

    def pages(self, packet: bytes, granule: int, first: bool = False, last: bool = False) -> Iterator[bytes]:
        laces = bytes([255]) * (len(packet) // 255) + bytes([len(packet) % 255])
        at, flags = 0, FIRST * first
        for i in range(0, len(laces), MOST_LACES):
            own = laces[i : i + MOST_LACES]
            ends = i + MOST_LACES >= len(laces)
            body = packet[at : (at := at + sum(own))]
            head = _HEADER.pack(MAGIC, 0, flags | LAST * (last and ends), granule if ends else -1, self.serial, self.sequence, 0, len(own))
            page = head + own + body
            yield page[:22] + struct.pack("<I", page_crc(page)) + page[26:]
            self.sequence += 1
            flags = CONTINUED


@dataclass
class Stream:
    """What the reader has of a logical stream."""

    packets: list[bytes] = field(default_factory=list)
    granules: list[int] = field(default_factory=list)
    partial: bytes = b""
    next_page: int = 0
    ended: bool = False


def encode(payload: bytes, notes: dict[str, str] | None = None) -> bytes:
    """Payload samples and notes as one physical stream of two multiplexed logical streams."""
    if not payload or len(payload) % FRAME:
        raise OggError("the payload must be a positive multiple of the frame")
    audio, text = _Writer(1), _Writer(2)
    note = json.dumps(notes or {}, sort_keys=True).encode()
    out = [*audio.pages(_HEAD.pack(b"PCM8HEAD", 1, RATE, 8, len(payload)), 0, first=True), *text.pages(b"NOTEHEAD", 0, first=True)]
    for at in range(0, len(payload), PACKET):
        end = min(at + PACKET, len(payload))
        out += audio.pages(payload[at:end], end, last=end == len(payload))
        if not at:
            out += text.pages(note, end, last=True)
    return b"".join(out)


def demultiplex(data: bytes) -> dict[int, Stream]:
    """Logical streams by serial number; checks checksums, page numbers, continuation and ends."""
    streams: dict[int, Stream] = {}
    at = 0
    while at < len(data):
        if len(data) - at < 27 or data[at : at + 4] != MAGIC:
            raise OggError(f"no page at byte {at}")
        _, version, flags, granule, serial, number, crc, n = _HEADER.unpack_from(data, at)
        laces = data[at + 27 : at + 27 + n]
        body_at = at + 27 + n
        end = body_at + sum(laces)
        page = data[at:end]
        if version or end > len(data) or page_crc(page[:22] + b"\0\0\0\0" + page[26:]) != crc:
            raise OggError(f"checksum or length of the page at byte {at}")
        s = streams.setdefault(serial, Stream())
        if number != s.next_page or bool(flags & FIRST) != (number == 0) or bool(flags & CONTINUED) != bool(s.partial) or s.ended:
            raise OggError(f"page {number} of stream {serial} is out of order")
        s.next_page += 1
        size, begin, done = 0, body_at, 0
        for lace in laces:
            size += lace
            if lace < 255:
                s.packets.append(s.partial + data[begin : begin + size])
                s.granules.append(-1)
                s.partial, begin, size, done = b"", begin + size, 0, done + 1
        s.partial += data[begin : begin + size]
        if done:
            s.granules[-1] = granule
        s.ended = bool(flags & LAST)
        at = end
    if any(s.partial or not s.ended for s in streams.values()):
        raise OggError("a stream is cut off")
    return streams


@dataclass
class Media:
    payload: bytes
    rate: int
    notes: dict[str, str]
    times: list[float]


def decode(data: bytes) -> Media:
    """Samples, sampling rate, notes and the end time in seconds of each packet.

    A page states the granule position of the last packet that it ends; those of the packets before are
    counted by their samples, and every stated one is checked against the count.
    """
    kinds = {s.packets[0][:8]: s for s in demultiplex(data).values()}
    audio, text = kinds[b"PCM8HEAD"], kinds[b"NOTEHEAD"]
    _, _, rate, _, total = _HEAD.unpack(audio.packets[0])
    payload = b"".join(audio.packets[1:])
    ends = np.cumsum([len(p) for p in audio.packets[1:]]).tolist()
    if len(payload) != total or audio.granules[-1] != total or any(g not in (-1, e) for g, e in zip(audio.granules[1:], ends, strict=True)):
        raise OggError("samples and granule positions differ")
    return Media(payload, rate, json.loads(text.packets[1]), [e / rate for e in ends])


def feature(samples: np.ndarray, rate: int, times: list[float]) -> str:
    """Mean, spread, sign changes about the middle, and length of the samples, as text."""
    values = samples.astype(np.float32)
    mean = float(samples.mean(dtype=np.float64))
    crossings = int(np.count_nonzero(np.diff(samples >= 128)))
    return f"mean={mean:.4f};sd={float(values.std(dtype=np.float64)):.4f};crossings={crossings};packets={len(times)};seconds={times[-1] if times else 0:.6f}"


def padded(raw: bytes) -> bytes:
    """With spaces up to a positive multiple of the frame."""
    return raw + b" " * (-len(raw) % FRAME if raw else FRAME)


def store(text: str | None) -> bytes:
    """A text as media bytes."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    return encode(padded(raw), {"bytes": str(len(raw))})


def store_column(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, media): every text as an Ogg file."""
    kind = docs.schema[id_col].dataType.simpleString()
    return per_row(docs, lambda: lambda i, t: (i, store(t)), f"doc_id {kind}, media binary", id_col, text_col)


def report(docs: DataFrame) -> DataFrame:
    """Stores every text, reads the stored bytes back and describes them; map-only."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def each(doc, text):
        media = store(text)
        back = decode(media)
        payload = back.payload
        return (
            doc,
            int(back.notes["bytes"]),
            len(payload),
            hashlib.sha256(payload).hexdigest(),
            zlib.crc32(payload[-16:]),
            len(media),
            hashlib.sha256(media).hexdigest(),
            feature(np.frombuffer(payload, np.uint8), back.rate, back.times),
        )

    return per_row(docs, lambda: each, f"doc_id {kind}, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string")
