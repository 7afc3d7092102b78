"""Ogg container as a lossless media column: write, verify, reassemble, demultiplex and time.

A payload of 8-bit samples is cut in 576-byte packets of one logical stream; a second logical stream carries the true
length. Both are multiplexed page by page. The reader checks every page's checksum and sequence number, joins lacing values
to packets (also across pages), separates streams by serial number and derives times from granule positions.

Nulls and empty texts give a payload of one packet of fill bytes. Equal texts give equal bytes. A damaged page raises
``ValueError``. Rows repeat, tie or carry extra columns without effect: only ``doc_id`` and ``text`` are read.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ._util import ship, slices

PACKET, RATE, FILL = 576, 8000, b"\xff"
SAMPLES, LENGTHS = 1, 2
_FLIP = bytes(int(f"{i:08b}"[::-1], 2) for i in range(256))


def page_checksum(page: bytes) -> int:
    """CRC with polynomial 0x04c11db7, most significant bit first, zero start: the zlib register mirrored."""
    mirrored = zlib.crc32(page.translate(_FLIP), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(mirrored.to_bytes(4, "little").translate(_FLIP), "big")


def _page(flags: int, granule: int, serial: int, number: int, lacing: bytes, body: bytes) -> bytes:
    head = struct.pack("<4sBBqIIIB", b"OggS", 0, flags, granule, serial, number, 0, len(lacing)) + lacing
    crc = page_checksum(head + body)
    return head[:22] + crc.to_bytes(4, "little") + head[26:] + body


def lace(size: int) -> bytes:
    return b"\xff" * (size // 255) + bytes([size % 255])


def write(payload: bytes, length: int) -> bytes:
    """Ogg bytes of a payload whose size is a positive multiple of 576; ``length``: bytes before the fill."""
    one, per_page = lace(PACKET), 255 // len(lace(PACKET))
    about = struct.pack("<8sIII", b"PCM8mono", RATE, PACKET, len(payload) // PACKET)
    size = struct.pack("<8sQ", b"TRUE_LEN", length)
    pages = [_page(2, 0, SAMPLES, 0, lace(len(about)), about), _page(2, 0, LENGTHS, 0, lace(8), b"LENGTHS1")]
    step, total, number = per_page * PACKET, len(payload), 1
    for at in range(0, total, step):
        body = payload[at : at + step]
        last = at + step >= total
        pages.append(_page(4 if last else 0, at + len(body), SAMPLES, number, one * (len(body) // PACKET), body))
        if number == 1:
            pages.append(_page(4, total, LENGTHS, 1, lace(len(size)), size))
        number += 1
    return b"".join(pages)


def read(data: bytes) -> dict[int, list[tuple[bytes, int]]]:
    """Packets of each logical stream with the granule position of the page that ends them (-1: not the last there)."""
    streams: dict[int, list[tuple[bytes, int]]] = {}
    parts: dict[int, list[bytes]] = {}
    expect: dict[int, int] = {}
    at = 0
    while at < len(data):
        if len(data) - at < 27 or data[at : at + 5] != b"OggS\0":
            raise ValueError(f"no page at byte {at}")
        _, _, flags, granule, serial, number, crc, segments = struct.unpack_from("<4sBBqIIIB", data, at)
        lacing = data[at + 27 : at + 27 + segments]
        start = at + 27 + segments
        end = start + sum(lacing)
        if end > len(data) or len(lacing) < segments:
            raise ValueError(f"page at byte {at} is cut short")
        if page_checksum(data[at : at + 22] + b"\0\0\0\0" + data[at + 26 : end]) != crc:
            raise ValueError(f"checksum of the page at byte {at}")
        if number != expect.get(serial, 0):
            raise ValueError(f"stream {serial}: page {number} is out of order")
        expect[serial] = number + 1
        open_part = parts.setdefault(serial, [])
        if bool(flags & 1) != bool(open_part):
            raise ValueError(f"stream {serial}: continuation flag of page {number}")
        out = streams.setdefault(serial, [])
        ends = start + np.cumsum(np.frombuffer(lacing, np.uint8).astype(np.int64))
        cut = ends[np.frombuffer(lacing, np.uint8) < 255].tolist()
        for i, stop in enumerate(cut):
            out.append((b"".join([*open_part, data[start:stop]]), granule if i == len(cut) - 1 else -1))
            open_part.clear()
            start = stop
        if start < end:
            open_part.append(data[start:end])
        at = end
    if any(parts.values()):
        raise ValueError("the last packet is not closed")
    return streams


def decode(data: bytes) -> tuple[bytes, int, str]:
    """Payload, true length and a feature string of stored bytes."""
    streams = read(data)
    about, frames = streams[SAMPLES][0][0], streams[SAMPLES][1:]
    _, rate, packet, count = struct.unpack("<8sIII", about)
    payload = b"".join(p for p, _ in frames)
    if len(frames) != count or len(payload) != packet * count or frames[-1][1] != len(payload):
        raise ValueError("packets or granule positions disagree with the stream header")
    length = struct.unpack("<8sQ", streams[LENGTHS][1][0])[1]
    wave = np.frombuffer(payload, np.uint8)
    counts = np.bincount(wave, minlength=256)
    values = np.arange(256, dtype=np.int64)
    mean = float((counts * values).sum() / len(wave))
    rms = float(np.sqrt((counts * (values - 128) ** 2).sum() / len(wave)))
    stamps = [g / rate for _, g in frames if g >= 0]
    feature = f"streams={len(streams)};packets={count};pages={len(stamps)};seconds={len(payload) / rate:.6f};first_page_end={stamps[0]:.6f};mean={mean:.6f};rms={rms:.6f};peak={int(wave.max())}"
    return payload, length, feature


SCHEMA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def media_rows(docs: DataFrame) -> DataFrame:
    """Digest row per document of its text stored as Ogg and read back."""
    ship(docs.sparkSession)

    def work(batches):
        for batch, texts in slices(batches):
            rows = []
            for t in texts:
                raw = t.encode("utf-8", "surrogatepass")
                fill = PACKET if not raw else -len(raw) % PACKET
                media = write(raw + FILL * fill, len(raw))
                payload, length, feature = decode(media)
                rows.append((length, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(media), hashlib.sha256(media).hexdigest(), feature))
            cols = list(zip(*rows, strict=True))
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names=[x.split()[0] for x in SCHEMA.split(", ")])

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(work, SCHEMA)


def media_column(docs: DataFrame) -> DataFrame:
    """General form: the stored bytes themselves, one binary ``media`` column per document."""
    ship(docs.sparkSession)

    def work(batches):
        for batch, texts in slices(batches, limit=4 << 20):
            out = []
            for t in texts:
                raw = t.encode("utf-8", "surrogatepass")
                out.append(write(raw + FILL * (PACKET if not raw else -len(raw) % PACKET), len(raw)))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(out, pa.binary())], names=["doc_id", "media"])

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(work, "doc_id long, media binary")
