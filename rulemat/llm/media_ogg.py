"""Media columns: an Ogg container writer and reader over binary columns.

Writing: a text's bytes, padded with zeros to a positive multiple of 64, are 8-bit mono
samples of one logical stream; a second logical stream carries a note with the unpadded
length.  Both are cut into packets, packets into lacing segments, segments into pages with
sequence numbers, granule positions and checksums, and the pages are interleaved.

Reading: pages are found by their capture pattern and checked by checksum and sequence,
streams are separated by serial number, packets are put together from lacing values (also
across pages), and times follow from granule positions and the sample rate.  A page that
fails its checksum is left out and counted, reading goes on at the next capture pattern.

Defined cases: null text is empty; equal texts give equal files, as serial numbers derive
from the content; a file without readable pages yields no streams.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean_heap, resting

RATE = 8000
PACKET = 4096
_AUDIO, _NOTES = b"PCMU8\0\0\1", b"NOTES\0\0\1"
_CONTINUED, _FIRST, _LAST = 1, 2, 4
_REVERSED = bytes(int(f"{b:08b}"[::-1], 2) for b in range(256))


def page_checksum(page: bytes) -> int:
    """The container's CRC-32 (polynomial 04C11DB7, most significant bit first, zero start,
    no final inversion), by way of the reflected one that zlib computes."""
    x = zlib.crc32(page.translate(_REVERSED), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(x.to_bytes(4, "little").translate(_REVERSED), "big")


def _page(flags: int, granule: int, serial: int, seq: int, lacing: bytes, body: bytes) -> bytes:
    head = struct.pack("<4sBBqIIIB", b"OggS", 0, flags, granule, serial, seq, 0, len(lacing)) + lacing
    return head[:22] + struct.pack("<I", page_checksum(head + body)) + head[26:] + body


def pages_of(serial: int, packets: list[bytes], granules: list[int], head: int = 1) -> list[bytes]:
    """The pages of one logical stream; the first ``head`` packets get a page each."""
    out: list[bytes] = []
    lacing, body, granule, flags = bytearray(), [], -1, 0

    def close(last: bool) -> None:
        nonlocal lacing, body, granule, flags
        out.append(_page(flags | _FIRST * (not out) | _LAST * last, granule, serial, len(out), bytes(lacing), b"".join(body)))
        lacing, body, granule, flags = bytearray(), [], -1, 0

    for k, (packet, at) in enumerate(zip(packets, granules, strict=True)):
        left = len(packet) // 255 + 1
        pos = 0
        while left:
            if len(lacing) == 255:
                close(False)
                flags = _CONTINUED if pos else 0
            take = min(left, 255 - len(lacing))
            size = min(len(packet) - pos, take * 255)
            lacing += b"\xff" * (take - 1) + bytes([255 if left > take else size - 255 * (take - 1)])
            body.append(packet[pos : pos + size])
            pos, left = pos + size, left - take
        granule = at
        if k < head:
            close(len(packets) == k + 1)
    if lacing:
        close(True)
    return out


def write_media(raw: bytes) -> bytes:
    """The stored form of a payload."""
    padded = raw + bytes(-len(raw) % 64 or 64 * (not raw))
    serial = zlib.crc32(padded)
    parts = [padded[i : i + PACKET] for i in range(0, len(padded), PACKET)]
    audio = pages_of(serial, [_AUDIO + struct.pack("<IB", RATE, 1), *parts], [0, *(min(len(padded), (i + 1) * PACKET) for i in range(len(parts)))])
    notes = pages_of(serial ^ 0x5A5A5A5A, [_NOTES, struct.pack("<Q", len(raw))], [0, 0])
    return b"".join([audio[0], notes[0], *notes[1:], *audio[1:]])


class Stream:
    __slots__ = ("bad", "end", "granule", "held", "packets", "pages", "seq")

    def __init__(self) -> None:
        self.packets: list[tuple[bytes, int, int]] = []  # packet, granule of its page, packet's rank on it from the end
        self.held: list[bytes] | None = []
        self.pages, self.seq, self.granule, self.bad, self.end = 0, 0, -1, 0, False


def read_media(media: bytes) -> tuple[dict[int, Stream], int]:
    """Logical streams by serial number, and the number of unreadable pages."""
    streams: dict[int, Stream] = {}
    at, bad = 0, 0
    while (at := media.find(b"OggS", at)) >= 0:
        if at + 27 > len(media):
            bad += 1
            break
        _, version, flags, granule, serial, seq, crc, n = struct.unpack_from("<4sBBqIIIB", media, at)
        lacing = media[at + 27 : at + 27 + n]
        size = 27 + n + sum(lacing)
        page = media[at : at + size]
        if version or len(page) < size or page_checksum(page[:22] + b"\0\0\0\0" + page[26:]) != crc:
            bad += 1
            at += 4
            continue
        s = streams.setdefault(serial, Stream())
        if seq != s.seq:  # a page is missing: what was open can't be completed
            s.bad += 1
            s.held = None if flags & _CONTINUED else []
        elif not flags & _CONTINUED:
            s.held = []
        pos, start, first = 27 + n, 27 + n, len(s.packets)
        for x in lacing:
            pos += x
            if x < 255:
                if s.held is not None:
                    s.packets.append((b"".join([*s.held, page[start:pos]]), granule, 0))
                s.held, start = [], pos
        if start < pos and s.held is not None:
            s.held.append(page[start:pos])
        done = len(s.packets)
        for k in range(first, done):
            s.packets[k] = (s.packets[k][0], granule, done - 1 - k)
        s.pages, s.seq, s.end = s.pages + 1, seq + 1, s.end or bool(flags & _LAST)
        s.granule = max(s.granule, granule)
        at += size
    return streams, bad


def times(s: Stream, rate: int = RATE) -> list[float]:
    """End time in seconds of each data packet: its page's granule position less the
    samples of the packets that end after it on that page."""
    out: list[float] = []
    later = 0
    for packet, granule, rank in reversed(s.packets[1:]):
        later = 0 if rank == 0 else later
        out.append((granule - later) / rate)
        later += len(packet)
    return out[::-1]


def describe(media: bytes) -> tuple[int, bytes, str]:
    """(unpadded length, payload, feature) read from the stored form."""
    streams, bad = read_media(media)
    raw, payload, feature = 0, b"", f"bad={bad}"
    for s in streams.values():
        if s.packets and s.packets[0][0].startswith(_NOTES) and len(s.packets) > 1:
            (raw,) = struct.unpack("<Q", s.packets[1][0])
    for s in streams.values():
        if s.packets and s.packets[0][0].startswith(_AUDIO):
            (rate, _) = struct.unpack_from("<IB", s.packets[0][0], len(_AUDIO))
            payload = b"".join(p for p, _, _ in s.packets[1:])
            x = np.frombuffer(payload, np.uint8).astype(np.int32) - 128
            t = times(s, rate)
            feature = f"pages={s.pages};packets={len(s.packets) - 1};streams={len(streams)};ms={round(1000 * t[-1]) if t else 0};power={int((x * x).sum(dtype=np.int64)) // max(1, len(x))};crossings={int(((x[1:] < 0) != (x[:-1] < 0)).sum())};bad={bad + s.bad};end={int(s.end)}"
    return raw, payload, feature


def encode_media(docs: DataFrame) -> DataFrame:
    """(doc_id, media): each text's bytes in their stored form."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean_heap()
        for batch in batches:
            texts = batch.column(1)
            step = max(1, min(len(texts), 2000))
            for k in range(0, len(texts), step):
                part = texts.slice(k, step)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(k, step), pa.array([write_media((x.as_py() or b"")) for x in part.cast(pa.binary())], pa.binary())], names=["doc_id", "media"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(resting(run), "doc_id long, media binary")


_FEATURES = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def decode_media(media: DataFrame) -> DataFrame:
    """Features of a media column, computed from the stored bytes alone."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean_heap()
        for batch in batches:
            rows = []
            for x in batch.column(1):
                blob = x.as_py() or b""
                raw, payload, feature = describe(blob)
                rows.append((raw, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(blob), hashlib.sha256(blob).hexdigest(), feature))
            cols = list(zip(*rows, strict=True)) or [()] * 7
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names=[x.split()[0] for x in _FEATURES.split(", ")])

    return media.select("doc_id", "media").mapInArrow(resting(run), _FEATURES)


def media_digests(docs: DataFrame) -> DataFrame:
    return decode_media(encode_media(docs))
