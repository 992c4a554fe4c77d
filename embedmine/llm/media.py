"""Media columns in Ogg: pages with checksums, lacing, logical streams, granule positions.

A payload becomes one physical stream of two logical ones. The *sample* stream
holds the payload as unsigned 8-bit samples; its granule position counts
samples, so a packet's time is the position over the rate. The *index* stream
holds, for every 16 sample packets, their end position and CRC-32. Reading
verifies every page's checksum, looks for the next page where one is damaged,
separates the streams by serial number, and joins packets from their lacing
values, over page ends as well.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_value

by_value(__name__)

#: Fixed values of the page format: mark, header layout, flags.
MARK, HEADER = b"OggS", "<4sBBqIIIB"
HEADER_SIZE, CONTINUED, BEGINS, ENDS = 27, 1, 2, 4
SAMPLES, INDEX = b"PCM8", b"IDX0"
RATE, PACKET, INDEXED, ALIGN = 8000, 4096, 16, 64
MIRROR = bytes(int(f"{i:08b}"[::-1], 2) for i in range(256))


def page_crc(data: bytes) -> int:
    """CRC-32 with the high bit first, started at 0: the mirror image of zlib's on mirrored bytes."""
    c = zlib.crc32(data.translate(MIRROR), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(c.to_bytes(4, "little").translate(MIRROR), "big")


class Writer:
    """Pages of one logical stream."""

    def __init__(self, serial: int):
        self.serial, self.number = serial, 0
        self.open_flag = BEGINS

    def pages(self, packets: list[tuple[bytes, int]], last: bool = False) -> list[bytes]:
        """(packet, granule position at its end) to pages; the last of them ends the stream if ``last``."""
        segments = []  # (piece, position if the packet ends here, begins a packet)
        for data, position in packets:
            for i in range(0, len(data) + 1, 255):
                piece = data[i : i + 255]
                segments.append((piece, position if len(piece) < 255 else None, i == 0))
        out = []
        for i in range(0, len(segments), 255):
            held = segments[i : i + 255]
            flags = self.open_flag | (0 if held[0][2] else CONTINUED) | (ENDS if last and i + 255 >= len(segments) else 0)
            position = next((p for _, p, _ in reversed(held) if p is not None), -1)
            body = b"".join(x[0] for x in held)
            lacing = bytes(len(x[0]) for x in held)
            head = struct.pack(HEADER, MARK, 0, flags, position, self.serial, self.number, 0, len(held)) + lacing
            crc = page_crc(head + body)
            out.append(head[:22] + crc.to_bytes(4, "little") + head[26:] + body)
            self.number += 1
            self.open_flag = 0
        return out


@dataclass
class Stream:
    """A logical stream as read: packets, (packet number, granule position) at page ends, faults."""

    packets: list[bytes] = field(default_factory=list)
    marks: list[tuple[int, int]] = field(default_factory=list)
    pages: int = 0
    lost: int = 0
    ended: bool = False
    partial: list[bytes] | None = None
    next_page: int = 0

    def times(self, rate: int = RATE) -> list[float]:
        """Seconds at the end of each page on which a packet ends."""
        return [position / rate for _, position in self.marks]


def write_ogg(payload: bytes, rate: int = RATE) -> bytes:
    serial = zlib.crc32(payload)
    samples, index = Writer(serial), Writer(serial ^ 0xFFFFFFFF)
    out = samples.pages([(SAMPLES + struct.pack("<IBQ", rate, 1, len(payload)), 0)])
    out += index.pages([(INDEX + struct.pack("<IH", serial, INDEXED), 0)])
    step = PACKET * INDEXED
    for begin in range(0, max(1, len(payload)), step):
        part = payload[begin : begin + step]
        end = begin + len(part)
        last = end >= len(payload)
        out += samples.pages([(part[i : i + PACKET], begin + min(i + PACKET, len(part))) for i in range(0, max(1, len(part)), PACKET)], last)
        out += index.pages([(struct.pack("<QI", end, zlib.crc32(part)), end)], last)
    return b"".join(out)


def read_streams(data: bytes) -> tuple[dict[int, Stream], int]:
    """Logical streams by serial number, and the number of damaged or foreign stretches skipped."""
    streams: dict[int, Stream] = {}
    bad, at = 0, 0
    while at < len(data):
        ok = data.startswith(MARK, at) and len(data) - at >= HEADER_SIZE
        if ok:
            _, version, flags, position, serial, number, crc, count = struct.unpack_from(HEADER, data, at)
            body = at + HEADER_SIZE + count
            lacing = data[at + HEADER_SIZE : body]
            end = body + sum(lacing)
            ok = version == 0 and len(lacing) == count and end <= len(data)
            ok = ok and page_crc(data[at : at + 22] + bytes(4) + data[at + 26 : end]) == crc
        if not ok:
            bad += 1
            at = data.find(MARK, at + 1)
            if at < 0:
                break
            continue
        s = streams.setdefault(serial, Stream())
        if number != s.next_page:
            s.lost += 1
            s.partial = None
        s.next_page, s.pages, s.ended = number + 1, s.pages + 1, bool(flags & ENDS)
        skip = bool(flags & CONTINUED) and s.partial is None
        if not flags & CONTINUED:
            s.partial = None
        done = False
        for size in lacing:
            if not skip:
                s.partial = s.partial or []
                s.partial.append(data[body : body + size])
            body += size
            if size < 255:
                if not skip:
                    s.packets.append(b"".join(s.partial))
                    s.partial, done = None, True
                skip = False
        if done and position >= 0:
            s.marks.append((len(s.packets), position))
        at = end
    return streams, bad


def read_ogg(data: bytes) -> tuple[bytes | None, dict]:
    """The payload, and what was found; the payload is None unless every check holds."""
    streams, bad = read_streams(data)
    samples = next((s for s in streams.values() if s.packets and s.packets[0].startswith(SAMPLES)), None)
    index = next((s for s in streams.values() if s.packets and s.packets[0].startswith(INDEX)), None)
    info = {"streams": len(streams), "damaged": bad, "pages": sum(s.pages for s in streams.values()), "lost": sum(s.lost for s in streams.values())}
    if samples is None or len(samples.packets[0]) < 17:
        return None, info
    rate, _, size = struct.unpack_from("<IBQ", samples.packets[0], 4)
    payload = b"".join(samples.packets[1:])
    info |= {"rate": rate, "packets": len(samples.packets) - 1, "seconds": samples.times(rate)[-1] if samples.marks and rate else 0.0}
    begin, sound = 0, index is not None and not bad and not info["lost"] and samples.ended and len(payload) == size
    for entry in index.packets[1:] if index else ():
        end, crc = struct.unpack_from("<QI", entry)
        sound = sound and zlib.crc32(payload[begin:end]) == crc
        begin = end
    return (payload if sound and begin == size else None), info


def padded(text: str | None) -> tuple[int, bytes]:
    data = (text or "").encode()
    return len(data), data + bytes(max(ALIGN, -(-len(data) // ALIGN) * ALIGN) - len(data))


def describe(payload: bytes, info: dict) -> str:
    """Measures of the samples that were read back: level, range, crossings of the middle, spread over 8 bands."""
    x = np.frombuffer(payload, np.uint8)
    level = x.astype(np.float32) - 128
    crossings = int(np.count_nonzero((x[1:] >= 128) != (x[:-1] >= 128)))
    bands = np.bincount(x >> 5, minlength=8)
    return f"streams={info['streams']};pages={info['pages']};packets={info['packets']};seconds={info['seconds']:.4f};mean={float(level.mean()):.3f};rms={float(np.sqrt((level * level).mean())):.3f};low={x.min()};high={x.max()};crossings={crossings};bands={'-'.join(map(str, bands))}"


def to_ogg(df: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The ``keep`` columns with n_bytes and media, the Ogg stream of the padded text (null: empty)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for begin in range(0, batch.num_rows, 256):
                part = batch.slice(begin, 256)
                pairs = [padded(t.as_py()) for t in part.column(len(keep))]
                yield pa.RecordBatch.from_arrays([*part.columns[: len(keep)], pa.array([n for n, _ in pairs], pa.int64()), pa.array([write_ogg(p) for _, p in pairs], pa.binary())], names=[*keep, "n_bytes", "media"])

    schema = ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in keep)
    return df.select(*keep, F.col(text).alias("__text")).mapInArrow(run, f"{schema}, n_bytes long, media binary")


def media_features(df: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """Every row's text stored as Ogg, read back and measured: doc_id, n_bytes, payload_bytes,
    payload_sha256, tail_crc32, media_bytes, media_sha256, feature. Equal texts have equal values;
    a stream that does not read back as written ends the job with an error."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for text in batch.column(1):
                n, payload = padded(text.as_py())
                media = write_ogg(payload)
                back, info = read_ogg(media)
                if back is None:
                    raise ValueError(f"the stored stream cannot be read back: {info}")
                rows.append((n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(media), hashlib.sha256(media).hexdigest(), describe(back, info)))
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)]], names=["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    kind = df.schema[doc_id].dataType.simpleString()
    return df.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, f"doc_id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


def read_media(df: DataFrame, media: str = "media", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, sound, payload, streams, pages, damaged, lost, seconds of a column of Ogg streams.

    Null or unreadable bytes give sound = false and a null payload.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [read_ogg(x.as_py() or b"") for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([p is not None for p, _ in found]), pa.array([p for p, _ in found], pa.binary()), *[pa.array([i[k] for _, i in found], pa.int64()) for k in ("streams", "pages", "damaged", "lost")], pa.array([i.get("seconds") for _, i in found], pa.float64())],
                names=["doc_id", "sound", "payload", "streams", "pages", "damaged", "lost", "seconds"],
            )

    kind = df.schema[doc_id].dataType.simpleString()
    return df.select(F.col(doc_id).alias("doc_id"), F.col(media).alias("media")).mapInArrow(run, f"doc_id {kind}, sound boolean, payload binary, streams long, pages long, damaged long, lost long, seconds double")
