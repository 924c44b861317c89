"""Media column: payloads in Ogg containers.

``write_stream`` lays packets out on pages (lacing values, continued packets, granule positions,
page checksums), ``mux`` interleaves logical streams, ``demux`` verifies every page and gives each
stream's packets and timestamps back.

Cases: a null text is an empty text; an empty text becomes 64 zero samples; equal texts give equal
bytes (serial numbers derive from the content); a null doc_id is passed on; an empty table gives an
empty result; other columns of the input are not looked at.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from prefixcode.llm.common import id_text, slices, table

RATE = 8000  # samples a second; only the scale of timestamps
PACKET = 8192  # samples in a packet: 33 lacing values, so packets run over page ends
_HEADER = struct.Struct("<4sBBqIIIB")
_REVERSED = bytes(int(f"{b:08b}"[::-1], 2) for b in range(256))
_MARK = struct.Struct("<QI")


class OggError(ValueError):
    """A page or a stream that isn't whole."""


def page_checksum(page: bytes) -> int:
    """CRC-32 with polynomial 04c11db7, not reflected, register zero at the start and no final xor.

    The C library's CRC is the reflected twin, so the bytes' bits are mirrored on the way in and the
    register's bits on the way out.
    """
    mirrored = zlib.crc32(page.translate(_REVERSED), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(mirrored.to_bytes(4, "little").translate(_REVERSED), "big")


def _page(flags: int, granule: int, serial: int, number: int, lacing: bytes, body: bytes) -> bytes:
    head = _HEADER.pack(b"OggS", 0, flags, granule, serial, number, 0, len(lacing)) + lacing
    crc = page_checksum(head + body)
    return head[:22] + struct.pack("<I", crc) + head[26:] + body


def write_stream(serial: int, packets: list[tuple[bytes, int]]) -> list[bytes]:
    """Pages of one logical stream. packets: (data, granule position at its end).

    The first packet has a page of its own, as stream headers must.
    """
    pages: list[bytes] = []
    lacing, body, granule, fresh = bytearray(), bytearray(), -1, True

    def flush(continued: bool, last: bool) -> None:
        nonlocal lacing, body, granule
        flags = continued | 2 * (not pages) | 4 * last
        pages.append(_page(flags, granule, serial, len(pages), bytes(lacing), bytes(body)))
        lacing, body, granule = bytearray(), bytearray(), -1

    continued = False
    for k, (data, end) in enumerate(packets):
        values = bytes([255]) * (len(data) // 255) + bytes([len(data) % 255])
        at = 0
        while at < len(values):
            if len(lacing) == 255:
                flush(continued, False)
                continued = at > 0
            take = values[at : at + 255 - len(lacing)]
            lacing += take
            body += data[at * 255 : (at + len(take)) * 255]
            at += len(take)
        granule = end
        if k == 0 or k == len(packets) - 1:
            flush(continued, k == len(packets) - 1)
            continued = False
    return pages


def mux(streams: list[list[bytes]]) -> bytes:
    """All first pages before any other page, then page by page in turn."""
    out = [s[0] for s in streams]
    for k in range(1, max(len(s) for s in streams)):
        out += [s[k] for s in streams if k < len(s)]
    return b"".join(out)


def pages_of(media: bytes) -> Iterator[tuple[int, int, int, int, bytes, memoryview]]:
    """(flags, granule, serial, number, lacing, body) of each page, its checksum verified."""
    at, view = 0, memoryview(media)
    while at < len(media):
        if len(media) - at < 27:
            raise OggError("a page's header is cut short")
        magic, version, flags, granule, serial, number, crc, count = _HEADER.unpack_from(media, at)
        if magic != b"OggS" or version:
            raise OggError(f"no page at byte {at}")
        lacing = bytes(view[at + 27 : at + 27 + count])
        start = at + 27 + count
        end = start + sum(lacing)
        if len(lacing) < count or end > len(media):
            raise OggError("a page's body is cut short")
        if page_checksum(b"".join((view[at : at + 22], b"\0\0\0\0", view[at + 26 : end]))) != crc:
            raise OggError(f"wrong checksum of page {number} of stream {serial}")
        yield flags, granule, serial, number, lacing, view[start:end]
        at = end


def demux(media: bytes) -> dict[int, list[tuple[bytes, int | None]]]:
    """serial -> packets, each with its granule position if it is the last to end on its page."""
    streams: dict[int, list[tuple[bytes, int | None]]] = {}
    partial: dict[int, bytearray | None] = {}
    expected: dict[int, int] = {}
    ended: set[int] = set()
    for flags, granule, serial, number, lacing, body in pages_of(media):
        if bool(flags & 2) == (serial in streams):
            raise OggError("a stream must begin with one first page")
        if number != expected.get(serial, 0) or serial in ended:
            raise OggError(f"page {number} of stream {serial} is out of sequence")
        packets = streams.setdefault(serial, [])
        rest = partial.get(serial)
        if bool(flags & 1) != (rest is not None):
            raise OggError("continued flag and open packet disagree")
        current = rest if rest is not None else bytearray()
        at, last = 0, None
        for k, value in enumerate(lacing):
            current += body[at : at + value]
            at += value
            if value < 255:
                packets.append((bytes(current), None))
                current, last = bytearray(), k
        if last is not None:
            packets[-1] = (packets[-1][0], granule)
        elif granule != -1:
            raise OggError("a page on which no packet ends has a granule position")
        partial[serial] = current if lacing and lacing[-1] == 255 else None
        expected[serial] = number + 1
        if flags & 4:
            ended.add(serial)
    if any(x is not None for x in partial.values()) or ended != set(streams):
        raise OggError("a stream isn't ended")
    return streams


def timestamps(packets: list[tuple[bytes, int | None]], rate: int, length=len) -> list[float]:
    """Seconds at each packet's end: granule positions where given, else counted back from the next."""
    out: list[float] = [0.0] * len(packets)
    known: int | None = None
    for k in range(len(packets) - 1, -1, -1):
        data, granule = packets[k]
        if granule is not None and granule >= 0:
            known = granule
        if known is None:
            raise OggError("no granule position follows a packet")
        out[k] = known / rate
        known -= length(data)
    return out


def pad(text: bytes, unit: int = 64) -> bytes:
    return text + bytes(max(unit, -(-len(text) // unit) * unit) - len(text))


def encode(payload: bytes, n_bytes: int) -> bytes:
    """Two logical streams: samples (8-bit, one channel), and running checksums as marks."""
    serial = zlib.crc32(payload)
    marks_serial = serial ^ 1
    samples = [(b"\x7fPCM8" + struct.pack("<IQ", RATE, n_bytes), 0)]
    marks = [(b"\x7fMARK" + struct.pack("<I", RATE), 0)]
    crc = 0
    for at in range(0, len(payload), PACKET):
        part = payload[at : at + PACKET]
        samples.append((part, at + len(part)))
        crc = zlib.crc32(part, crc)
        if (at // PACKET) % 16 == 15 or at + PACKET >= len(payload):
            marks.append((_MARK.pack(at + len(part), crc), at + len(part)))
    return mux([write_stream(serial, samples), write_stream(marks_serial, marks)])


def decode(media: bytes) -> tuple[bytes, int, list[float]]:
    """Payload, length of the text without padding, and the packets' end times; all verified."""
    streams = demux(media)
    kinds = {p[0][0][:5]: p for p in streams.values()}
    if set(kinds) != {b"\x7fPCM8", b"\x7fMARK"}:
        raise OggError("the streams aren't those that were written")
    head, *packets = kinds[b"\x7fPCM8"]
    rate, n_bytes = struct.unpack("<IQ", head[0][5:])
    payload = b"".join(p for p, _ in packets)
    for mark, _ in kinds[b"\x7fMARK"][1:]:
        end, crc = _MARK.unpack(mark)
        if zlib.crc32(memoryview(payload)[:end]) != crc:
            raise OggError("samples and marks disagree")
    return payload, n_bytes, timestamps(packets, rate)


def feature(payload: bytes, times: list[float]) -> str:
    """Duration, mean level, mean absolute step and a 16-band level histogram of the samples."""
    x = np.frombuffer(payload, dtype=np.uint8)
    bands = np.bincount(x >> 4, minlength=16)
    step = int(np.abs(np.diff(x.astype(np.int16))).sum()) if len(x) > 1 else 0
    return f"dur={times[-1]:.4f};packets={len(times)};mean={int(x.sum(dtype=np.int64)) / len(x):.4f};step={step / len(x):.4f};bands=" + ",".join(map(str, bands))


SCHEMA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_packets long, seconds double"


def _batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:

    for batch in slices(batches):
        rows = []
        for text in batch.column("text").to_pylist():
            raw = text.encode("utf-8", "surrogatepass")
            media = encode(pad(raw), len(raw))
            payload, n_bytes, times = decode(media)
            rows.append((n_bytes, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(media), hashlib.sha256(media).hexdigest(), feature(payload, times), len(times), times[-1]))
        cols = [batch.column("doc_id"), *(pa.array(c) for c in zip(*rows, strict=True))]
        yield pa.RecordBatch.from_arrays(cols, names=[f.split()[0] for f in SCHEMA.split(", ")])


def media_features(docs: DataFrame) -> DataFrame:
    """One row per document: what was stored, read back and measured. Map-only, no shuffle."""
    return id_text(docs).mapInArrow(_batches, SCHEMA)


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_features(table(spark, sf_dir, "documents"))
