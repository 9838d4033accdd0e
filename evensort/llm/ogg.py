"""Media columns as Ogg: pages with checksums, packets by lacing values, logical streams.

A file holds two interleaved logical streams: 8-bit unsigned mono samples and a small stream
of facts about them.  The writer cuts packets into segments of up to 255 bytes, packs up to
255 segments on a page and closes each page with its CRC.  The reader verifies every page's
CRC and number, searches the next capture pattern after a damaged one, rebuilds packets
from lacing values (across pages), sorts packets by stream, and derives times from
granule positions.

The page CRC (polynomial 0x04C11DB7, most significant bit first, start 0) is computed with
zlib's, which has the same polynomial bit-reversed: reverse the bits of each byte, undo
zlib's start value, reverse the result.

Defined cases: a null text is empty; an empty one is stored as 64 zero bytes; equal texts
give equal files (the streams' serial numbers are fixed); damaged pages are listed, their
packets left out; repeated rows are independent; other columns pass through.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql.types import BinaryType, IntegerType, LongType, StringType, StructField, StructType

from ._arrow import append_columns

RATE = 8000
#: 16 segments a packet, 15 packets a page: a full page is 255 segments.
PACKET = 4080
PAD = 64
SAMPLES, FACTS = 1, 2
CONTINUED, BEGIN, END = 1, 2, 4
#: The first packet of the samples: name, channels, rate.
MAGIC, HEADER = b"U8PCM", struct.Struct("<5sBI")

_REVERSED = bytes(int(f"{b:08b}"[::-1], 2) for b in range(256))


def crc(data: bytes) -> int:
    """The Ogg page checksum of ``data`` (its own field zeroed)."""
    made = zlib.crc32(data.translate(_REVERSED), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(made.to_bytes(4, "little").translate(_REVERSED), "big")


class StreamWriter:
    """Pages of one logical stream; ``granule`` is the position after a packet."""

    def __init__(self, serial: int):
        self.serial, self.number = serial, 0

    def page(self, lacing: bytes, body: bytes, granule: int, flags: int) -> bytes:
        head = struct.pack("<4sBBqIII", b"OggS", 0, flags, granule, self.serial, self.number, 0) + bytes([len(lacing)]) + lacing
        self.number += 1
        return head[:22] + crc(head + body).to_bytes(4, "little") + head[26:] + body

    def pages(self, packets: list[tuple[bytes, int]], begin: bool = False, end: bool = False) -> list[bytes]:
        """The pages that hold (packet, granule) pairs, packets longer than a page included."""
        made: list[bytes] = []
        lacing, body, granule, flags = bytearray(), bytearray(), -1, 0

        def close(last: bool) -> None:
            nonlocal lacing, body, granule, flags
            marks = flags | (BEGIN if begin and not made else 0) | (END if end and last else 0)
            made.append(self.page(bytes(lacing), bytes(body), granule, marks))
            lacing, body, granule, flags = bytearray(), bytearray(), -1, 0

        for n, (packet, position) in enumerate(packets):
            values = b"\xff" * (len(packet) // 255) + bytes([len(packet) % 255])
            at = 0
            while at < len(values):
                room = min(255 - len(lacing), len(values) - at)
                lacing += values[at : at + room]
                body += packet[at * 255 : (at + room) * 255]
                at += room
                if at == len(values):
                    granule = position
                if len(lacing) == 255 and (at < len(values) or n + 1 < len(packets)):
                    close(False)
                    flags = CONTINUED if at < len(values) else 0
        if lacing or not made:
            close(True)
        return made


def write(payload: bytes, n_bytes: int, rate: int = RATE, packet: int = PACKET) -> bytes:
    """An Ogg file of 8-bit samples ``payload``, of which the first ``n_bytes`` are content."""
    samples, facts = StreamWriter(SAMPLES), StreamWriter(FACTS)
    head = HEADER.pack(MAGIC, 1, rate)
    parts = samples.pages([(head, 0)], begin=True) + facts.pages([(b"FACTS", 0)], begin=True)
    cuts = range(0, len(payload), packet)
    data = samples.pages([(payload[c : c + packet], min(c + packet, len(payload))) for c in cuts], end=True)
    info = facts.pages([(b"n_bytes=%d" % n_bytes, len(payload))], end=True)
    return b"".join(parts + data[:1] + info + data[1:])


@dataclass
class Stream:
    packets: list[bytes] = field(default_factory=list)
    granules: list[int] = field(default_factory=list)
    held: bytearray | None = None
    number: int = 0
    ended: bool = False


@dataclass
class File:
    streams: dict[int, Stream]
    damaged: list[tuple[int, int]]
    missing: int


def read(data: bytes) -> File:
    """Logical streams of a file; damaged byte ranges and the number of missing pages."""
    streams: dict[int, Stream] = {}
    damaged: list[tuple[int, int]] = []
    missing, at = 0, 0
    while at < len(data):
        size = _page_size(data, at)
        if size is None:
            found = data.find(b"OggS", at + 1)
            stop = found if found >= 0 else len(data)
            if damaged and damaged[-1][1] == at:
                damaged[-1] = (damaged[-1][0], stop)
            else:
                damaged.append((at, stop))
            at = stop
            continue
        flags, granule, serial, number, _, n = struct.unpack_from("<BqIIIB", data, at + 5)
        s = streams.setdefault(serial, Stream())
        if number != s.number:
            missing += max(0, number - s.number)
            s.held = None
        s.number = number + 1
        s.ended |= bool(flags & END)
        if not flags & CONTINUED:
            s.held = bytearray()
        body, done = at + 27 + n, 0
        for value in data[at + 27 : body]:
            if s.held is not None:
                s.held += data[body : body + value]
            body += value
            if value < 255:
                if s.held is not None:
                    s.packets.append(bytes(s.held))
                    s.granules.append(-1)
                    done += 1
                s.held = bytearray()
        if done:
            s.granules[-1] = granule
        at += size
    return File(streams, damaged, missing)


def _page_size(data: bytes, at: int) -> int | None:
    """Bytes of the page at ``at`` if it is whole and its checksum holds."""
    if data[at : at + 5] != b"OggS\x00" or len(data) < at + 27:
        return None
    n = data[at + 26]
    if len(data) < at + 27 + n:
        return None
    size = 27 + n + sum(data[at + 27 : at + 27 + n])
    if len(data) < at + size:
        return None
    own = int.from_bytes(data[at + 22 : at + 26], "little")
    return size if crc(data[at : at + 22] + bytes(4) + data[at + 26 : at + size]) == own else None


def seconds(stream: Stream, rate: int = RATE) -> list[float | None]:
    """End time of each packet that ends a page, from its granule position."""
    return [g / rate if g >= 0 else None for g in stream.granules]


def feature(samples: bytes, end: float) -> str:
    """Duration, level, loudness and zero crossings of 8-bit samples as one line."""
    x = np.frombuffer(samples, np.uint8).astype(np.int64) - 128
    crossings = int(np.count_nonzero((x[1:] < 0) != (x[:-1] < 0))) if len(x) else 0
    power = int((x * x).sum()) / max(1, len(x))
    return f"seconds={end:.6f};mean={int(x.sum()) / max(1, len(x)):.4f};rms={power**0.5:.4f};crossings={crossings};peak={int(np.abs(x).max(initial=0))}"


MEDIA = StructType([StructField("media", BinaryType())])
FACT_FIELDS = StructType(
    [
        StructField("n_bytes", LongType()),
        StructField("payload_bytes", LongType()),
        StructField("payload_sha256", StringType()),
        StructField("tail_crc32", LongType()),
        StructField("media_bytes", LongType()),
        StructField("media_sha256", StringType()),
        StructField("feature", StringType()),
        StructField("damaged_pages", IntegerType()),
    ]
)


def encode(docs: DataFrame, text_col: str = "text", keep=None) -> DataFrame:
    """``docs`` with ``media``: the text's UTF-8 bytes, padded with zeros, as an Ogg file."""

    def kernel(texts):
        made = []
        for t in texts:
            t = t or b""
            made.append((write(t + bytes(-len(t) % PAD or (0 if t else PAD)), len(t)),))
        return made

    return append_columns(docs, [text_col], lambda: kernel, MEDIA, keep)


def decode(media: bytes) -> tuple[bytes, int | None, float, File]:
    """(samples, unpadded length, end in seconds, file) of an Ogg file made by ``write``.

    Never raises: of a damaged file come the samples of its sound pages, and no length if the
    page that has it is lost."""
    made = read(media)
    stream, facts = made.streams.get(SAMPLES, Stream()), made.streams.get(FACTS, Stream())
    # a damaged first page takes the header along: every packet left is data then
    headed = stream.packets[:1] if stream.packets and len(stream.packets[0]) == HEADER.size and stream.packets[0].startswith(MAGIC) else []
    rate = HEADER.unpack(headed[0])[2] if headed else RATE
    n = next((int(p[8:]) for p in facts.packets if p.startswith(b"n_bytes=") and p[8:].isdigit()), None)
    ends = [s for s in seconds(stream, rate or RATE) if s is not None]
    return b"".join(stream.packets[len(headed) :]), n, ends[-1] if ends else 0.0, made


def describe(media_rows: DataFrame, media_col: str = "media", keep=None) -> DataFrame:
    """The stored bytes read back: sizes, digests and features.  Null media has null facts;
    damaged media has those of its sound pages, and a null length if its page is lost."""

    def one(m):
        if m is None:
            return (None,) * len(FACT_FIELDS.fields)
        payload, n, end, made = decode(m)
        return (
            n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-PAD:]),
            len(m), hashlib.sha256(m).hexdigest(), feature(payload, end), len(made.damaged),
        )

    return append_columns(media_rows, [media_col], lambda: lambda ms: [one(m) for m in ms], FACT_FIELDS, keep)
