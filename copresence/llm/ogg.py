"""Ogg as a media column: write, verify, reassemble, demultiplex, time.

Reading: every page's checksum is verified; packets are put together again from lacing values, over page borders and
per logical stream; a packet that a lost or damaged page broke is dropped and counted, never joined wrongly. The last
packet that ends on a page has the page's granule position (samples so far) at its end; those before it on the page are
timed backwards from there by what the packets between hold, and a time is granule / rate.

The page checksum is a CRC-32 without reflection that starts at 0; it is got from the reflected CRC of the standard
library by reversing the bits of each byte before and of the result after.

Writing: a document's bytes, padded to a positive multiple of 64 with zeros, are unsigned 8-bit samples of one stream;
a second stream carries the byte count and a check value for each block of samples. A stream's head has its first page
for itself. Two streams are interleaved: both first pages, then by granule.

Defined cases: null text is empty (64 zero samples); a null or empty media value has no packets; damaged bytes never
raise; equal texts give equal bytes; other columns do not enter. A row is handled by itself, a batch at a time.
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

from copresence.ship import arrow_map

#: Fixed values of the container.
MAGIC, CONTINUED, FIRST, LAST = b"OggS", 1, 2, 4
HEADER = struct.Struct("<4sBBqIIIB")
RATE = 8000
PACKET = 4096  # samples a packet
BLOCK = 65536  # samples a check value
SEGMENTS = 128  # lacing values a page
UNIT = 64
SAMPLES, CHECKS = 1, 2  # stream serials

_REVERSED = bytes(int(f"{b:08b}"[::-1], 2) for b in range(256))


def page_checksum(data: bytes) -> int:
    reflected = zlib.crc32(data.translate(_REVERSED), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(reflected.to_bytes(4, "little").translate(_REVERSED), "big")


def _page(serial: int, number: int, kind: int, granule: int, lacing: list[int], body: bytes) -> bytes:
    blank = HEADER.pack(MAGIC, 0, kind, granule, serial, number, 0, len(lacing)) + bytes(lacing) + body
    return blank[:22] + struct.pack("<I", page_checksum(blank)) + blank[26:]


def stream_pages(serial: int, packets: list[tuple[bytes, int]], segments: int = SEGMENTS) -> list[tuple[int, bytes]]:
    """Pages of one logical stream from (packet, granule at its end), each with its order key (granule so far)."""
    lacing: list[tuple[int, int | None]] = []  # lacing value, granule if a packet ends here
    for data, granule in packets:
        full, rest = divmod(len(data), 255)
        lacing += [(255, None)] * full + [(rest, granule)]
    head = len(packets[0][0]) // 255 + 1 if packets else 0  # values of the first packet: no other shares a page with it
    edges = [*range(0, head, segments), *range(head, max(len(lacing), 1), segments), len(lacing)]
    body, pages, at, so_far = b"".join(p for p, _ in packets), [], 0, 0
    for number, (first, end) in enumerate(zip(edges, edges[1:], strict=False)):
        own = lacing[first:end]
        ended = [g for _, g in own if g is not None]
        size = sum(n for n, _ in own)
        kind = CONTINUED * (first > 0 and lacing[first - 1][1] is None) | FIRST * (first == 0) | LAST * (end >= len(lacing))
        so_far = ended[-1] if ended else so_far
        pages.append((so_far, _page(serial, number, kind, ended[-1] if ended else -1, [n for n, _ in own], body[at : at + size])))
        at += size
    return pages


def encode(text: str | None) -> tuple[bytes, int, bytes]:
    """Payload, its length without padding, and the container that holds it."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    payload = raw + bytes(-len(raw) % UNIT or (UNIT if not raw else 0))
    head = struct.pack("<8sIQ", b"samples8", RATE, len(payload))
    samples = [(head, 0)] + [(payload[i : i + PACKET], min(i + PACKET, len(payload))) for i in range(0, len(payload), PACKET)]
    checks = [(struct.pack("<8sQ", b"checks32", len(raw)), 0)] + [(struct.pack("<I", zlib.crc32(payload[i : i + BLOCK])), min(i + BLOCK, len(payload))) for i in range(0, len(payload), BLOCK)]
    one, two = stream_pages(SAMPLES, samples), stream_pages(CHECKS, checks)
    order = sorted([(i > 0, key, s, i, page) for s, pages in ((SAMPLES, one), (CHECKS, two)) for i, (key, page) in enumerate(pages)], key=lambda x: x[:4])
    return payload, len(raw), b"".join(x[-1] for x in order)


@dataclass
class Stream:
    packets: list[tuple[bytes, int]] = field(default_factory=list)  # data, granule (-1: none)
    open: bytearray | None = None
    number: int = -1
    lost: int = 0


@dataclass
class Media:
    streams: dict[int, Stream] = field(default_factory=dict)
    pages: int = 0
    damaged: int = 0


def decode(data: bytes | None) -> Media:
    """Read a container: only pages whose checksum holds count; anything else is skipped up to the next page."""
    out, data, at = Media(), data or b"", 0
    while (at := data.find(MAGIC, at)) >= 0:
        if at + HEADER.size > len(data):
            out.damaged += 1
            break
        _, version, kind, granule, serial, number, check, count = HEADER.unpack_from(data, at)
        lacing = data[at + HEADER.size : at + HEADER.size + count]
        start = at + HEADER.size + count
        end = start + sum(lacing)
        whole = data[at : at + 22] + b"\0\0\0\0" + data[at + 26 : end]
        if version or len(lacing) < count or end > len(data) or page_checksum(whole) != check:
            out.damaged += 1
            at += 4
            continue
        out.pages += 1
        _take(out.streams.setdefault(serial, Stream()), kind, granule, number, lacing, data[start:end])
        at = end
    for s in out.streams.values():
        s.lost += s.open is not None
        s.open = None
    return out


def _take(s: Stream, kind: int, granule: int, number: int, lacing: bytes, body: bytes) -> None:
    gap = s.number >= 0 and number != s.number + 1
    s.number = number
    if s.open is not None and (gap or not kind & CONTINUED):
        s.lost, s.open = s.lost + 1, None
    broken = bool(kind & CONTINUED) and s.open is None  # its head is missing
    part, at, ended = s.open if s.open is not None else bytearray(), 0, []
    s.open = None
    for n in lacing:
        part += body[at : at + n]
        at += n
        if n < 255:
            if broken:
                s.lost, broken = s.lost + 1, False
            else:
                ended.append(bytes(part))
            part = bytearray()
            s.open = None
        else:
            s.open = None if broken else part
    if ended:
        s.packets += [(p, -1) for p in ended[:-1]] + [(ended[-1], granule)]


#: Granule at which a packet starts, from its bytes and the granule at its end, by the first bytes of its stream's head.
STARTS = {b"samples8": lambda data, end: end - len(data), b"checks32": lambda _, end: max(end - 1, 0) // BLOCK * BLOCK}


def granules(packets: list[tuple[bytes, int]]) -> list[int | None]:
    """Granule at the end of each packet: the page's, or counted back from the next packet of a stream of known kind."""
    start = STARTS.get(packets[0][0][:8]) if packets else None
    out: list[int | None] = [None] * len(packets)
    for k in range(len(packets) - 1, -1, -1):
        if packets[k][1] >= 0:
            out[k] = packets[k][1]
        elif start and k + 1 < len(packets) and out[k + 1] is not None:
            out[k] = start(packets[k + 1][0], out[k + 1])
    return out


def timestamps(packets: list[tuple[bytes, int]], rate: int = RATE) -> list[float | None]:
    """Seconds at the end of each packet; None where neither its page nor a later packet of it tells."""
    return [None if g is None else g / rate for g in granules(packets)]


def features(samples: np.ndarray) -> str:
    """Whole numbers only, so that equal samples give equal text anywhere."""
    if not len(samples):
        return "n=0"
    x = samples.astype(np.int64)
    counts = np.bincount(samples, minlength=256)
    turns = int(np.count_nonzero(np.diff((samples >= 128).view(np.int8))))
    return f"n={len(x)};sum={x.sum()};energy={(x * x).sum()};peak={x.max()};mode={counts.argmax()};distinct={np.count_nonzero(counts)};turns={turns};move={np.abs(np.diff(x)).sum()}"


REPORT = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, pages long, damaged long, packets long, seconds double"
PACKETS = "media_id long, stream long, packet long, granule long, seconds double, data binary"


def _report(doc_id: int | None, text: str | None) -> tuple:
    stored = encode(text)[2]
    media = decode(stored)
    head, *data = media.streams[SAMPLES].packets
    payload = b"".join(p for p, _ in data)
    checks = media.streams[CHECKS].packets
    n_bytes = struct.unpack("<8sQ", checks[0][0])[1]
    rate = struct.unpack("<8sIQ", head[0])[1]
    if [struct.unpack("<I", c)[0] for c, _ in checks[1:]] != [zlib.crc32(payload[i : i + BLOCK]) for i in range(0, len(payload), BLOCK)]:
        raise ValueError("the samples read back differ from their check values")
    ends = granules(media.streams[SAMPLES].packets)
    if ends[-1] != len(payload):
        raise ValueError("the granule positions read back differ from the samples")
    return (doc_id, n_bytes, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-UNIT:]), len(stored), hashlib.sha256(stored).hexdigest(), features(np.frombuffer(payload, np.uint8)), media.pages, media.damaged, sum(len(s.packets) for s in media.streams.values()), ends[-1] / rate)


def _columns(rows: list[tuple], kinds: list[pa.DataType], names: list[str]) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) if rows else [()] * len(names)
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=names)


def media_report(docs: DataFrame) -> DataFrame:
    """Store each document's bytes, read them back and describe them: one row per document."""
    names = [x.split()[0] for x in REPORT.split(", ")]
    kinds = [{"long": pa.int64(), "string": pa.string(), "double": pa.float64()}[x.split()[1]] for x in REPORT.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, texts = b.column(0).to_pylist(), b.column(1)
            yield _columns([_report(i, texts[k].as_py()) for k, i in enumerate(ids)], kinds, names)

    return arrow_map(docs.select("doc_id", "text"), run, REPORT)


def to_media(docs: DataFrame) -> DataFrame:
    """docs(doc_id, text) -> media_id, media binary."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield _columns([(i, encode(t)[2]) for i, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)], [pa.int64(), pa.binary()], ["media_id", "media"])

    return arrow_map(docs.select("doc_id", "text"), run, "media_id long, media binary")


def demultiplex(media: DataFrame, rate: int = RATE) -> DataFrame:
    """media(media_id, media) -> a row per packet of every logical stream: media_id, stream, packet, granule, seconds, data."""
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.binary()]
    names = [x.split()[0] for x in PACKETS.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, m in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                found = decode(m.as_py())
                rows = [(i, serial, k, g, None if g is None else g / rate, p) for serial, s in sorted(found.streams.items()) for k, ((p, _), g) in enumerate(zip(s.packets, granules(s.packets), strict=True))]
                if rows:
                    yield _columns(rows, kinds, names)

    return arrow_map(media.select("media_id", "media"), run, PACKETS)
