"""Ogg media columns: payloads as samples in Ogg pages, and back.

Writing: a payload of 8-bit samples becomes one logical stream of packets, and
a second logical stream lists the packets' end positions; both are interleaved
in one physical stream.  Pages carry lacing values, granule positions (samples
complete at the page's end, -1 where no packet ends) and checksums.

Reading: every page's checksum is verified, packets are put together from lacing
values over page borders, logical streams are separated by serial number, and
timestamps come from granule positions.

Defined results: a null or empty payload is stored as one frame of blanks; a
broken medium gives a null payload and a status (``no_capture_pattern``,
``bad_checksum``, ``cut_short``, ``lost_page``, ``no_stream``, ``bad_length``)
instead of an error; null media have status ``null``.  Equal payloads, equal
bytes.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

from ..session import ship_package

#: Fixed values of the container format: capture pattern, header flags, limits.
CAPTURE, CONTINUED, FIRST, LAST, MAX_LACING = b"OggS", 1, 2, 4, 255
HEADER = struct.Struct("<4sBBqIIIB")
FRAME, FRAMES_PER_PACKET, RATE = 192, 10, 8000
MAGIC, INDEX_MAGIC = b"\x01samples", b"\x01packets"

_REVERSED = bytes(int(f"{b:08b}"[::-1], 2) for b in range(256))


def page_checksum(page: bytes) -> int:
    """CRC of polynomial 0x04C11DB7, most significant bit first, start 0.

    zlib's CRC has the same polynomial with bits in the opposite order, so it
    gives this one on bytes whose bits are turned round.
    """
    x = zlib.crc32(page.translate(_REVERSED), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(x.to_bytes(4, "little").translate(_REVERSED), "big")


def padded(payload: bytes | None) -> bytes:
    """The payload with blanks up to a positive multiple of a frame."""
    payload = payload or b""
    return payload + b" " * ((-len(payload)) % FRAME if payload else FRAME)


class _StreamWriter:
    def __init__(self, serial: int) -> None:
        self.serial, self.sequence, self.pages = serial, 0, []

    def page(self, lacing: bytes, body: bytes, granule: int, flags: int) -> None:
        head = HEADER.pack(CAPTURE, 0, flags, granule, self.serial, self.sequence, 0, len(lacing)) + lacing
        page = head + body
        self.pages.append(head[:22] + page_checksum(page).to_bytes(4, "little") + page[26:])
        self.sequence += 1

    def packets(self, packets: list[bytes], granules: list[int], last: bool) -> None:
        """Pages of up to 255 lacing values; a packet may go on in the next page."""
        lacing, body, granule, first_continues = bytearray(), [], -1, False
        for packet, done in zip(packets, granules, strict=True):
            values = b"\xff" * (len(packet) // 255) + bytes([len(packet) % 255])
            at = 0
            while values:
                room = MAX_LACING - len(lacing)
                part, values = values[:room], values[room:]
                lacing += part
                size = sum(part)
                body.append(packet[at : at + size])
                at += size
                if not values:
                    granule = done
                if len(lacing) == MAX_LACING:
                    end = not values and packet is packets[-1]
                    self.page(bytes(lacing), b"".join(body), granule, CONTINUED * first_continues + LAST * (last and end))
                    lacing, body, granule, first_continues = bytearray(), [], -1, bool(values)
        if lacing:
            self.page(bytes(lacing), b"".join(body), granule, CONTINUED * first_continues + LAST * last)


def write_ogg(payload: bytes) -> bytes:
    """A physical stream of two logical ones: the samples, and their packets' ends."""
    serial = zlib.crc32(payload)
    samples, index = _StreamWriter(serial), _StreamWriter(serial ^ 0xFFFFFFFF)
    step = FRAME * FRAMES_PER_PACKET
    packets = [payload[k : k + step] for k in range(0, len(payload), step)]
    ends = [min(k + step, len(payload)) for k in range(0, len(payload), step)]
    head = MAGIC + struct.pack("<II", RATE, len(payload) & 0xFFFFFFFF)
    samples.page(bytes([len(head)]), head, 0, FIRST)
    head = INDEX_MAGIC + struct.pack("<I", len(packets))
    index.page(bytes([len(head)]), head, 0, FIRST)
    samples.packets(packets, ends, last=True)
    index.packets([struct.pack(f"<{len(ends)}Q", *ends)], [len(payload)], last=True)
    # both first pages stand in front; the rest alternates
    out = [samples.pages[0], index.pages[0]]
    a, b = samples.pages[1:], index.pages[1:]
    for k in range(max(len(a), len(b))):
        out += a[k : k + 1] + b[k : k + 1]
    return b"".join(out)


class OggError(ValueError):
    pass


@dataclass
class LogicalStream:
    serial: int
    packets: list[bytes] = field(default_factory=list)
    #: granule position at each packet's end; pages give it for the last packet that ends in them, None for others
    granules: list[int | None] = field(default_factory=list)
    pages: int = 0
    ended: bool = False
    open: list[bytes] = field(default_factory=list)
    sequence: int = 0


def read_ogg(media: bytes) -> list[LogicalStream]:
    """Logical streams in order of their first pages."""
    streams: dict[int, LogicalStream] = {}
    at, total = 0, len(media)
    while at < total:
        if media[at : at + 4] != CAPTURE:
            raise OggError("no_capture_pattern")
        if at + HEADER.size > total:
            raise OggError("cut_short")
        _, _, flags, granule, serial, sequence, crc, n = HEADER.unpack_from(media, at)
        lacing = media[at + HEADER.size : at + HEADER.size + n]
        body = at + HEADER.size + n
        end = body + sum(lacing)
        if len(lacing) < n or end > total:
            raise OggError("cut_short")
        if page_checksum(media[at : at + 22] + b"\0\0\0\0" + media[at + 26 : end]) != crc:
            raise OggError("bad_checksum")
        if flags & FIRST:
            streams[serial] = LogicalStream(serial)
        if serial not in streams:
            raise OggError("no_stream")
        s = streams[serial]
        if sequence != s.sequence or bool(flags & CONTINUED) != bool(s.open):
            raise OggError("lost_page")
        s.sequence, s.pages = s.sequence + 1, s.pages + 1
        begin, done = body, len(s.packets)
        stop = body
        for value in lacing:
            stop += value
            if value < 255:
                s.packets.append(b"".join([*s.open, media[begin:stop]]))
                s.granules.append(None)
                s.open, begin = [], stop
        if begin < stop or (lacing and lacing[-1] == 255):
            s.open.append(media[begin:stop])
        if len(s.packets) > done:
            s.granules[-1] = granule
        s.ended |= bool(flags & LAST)
        at = end
    return list(streams.values())


def packet_ends(stream: LogicalStream) -> list[int]:
    """Granule position at each packet's end, from the pages' positions back over packet sizes (one sample a byte)."""
    ends: list[int] = [0] * len(stream.packets)
    later = None
    for k in range(len(ends) - 1, -1, -1):
        known = stream.granules[k]
        later = known if known is not None else (later - len(stream.packets[k + 1]) if later is not None else -1)
        ends[k] = later
    return ends


def read_samples(media: bytes | None) -> tuple[bytes | None, str, str]:
    """(payload, feature, status) of one medium."""
    if media is None:
        return None, "", "null"
    try:
        streams = read_ogg(media)
        data = next((s for s in streams if s.packets and s.packets[0].startswith(MAGIC)), None)
        index = next((s for s in streams if s.packets and s.packets[0].startswith(INDEX_MAGIC)), None)
        if data is None or index is None:
            raise OggError("no_stream")
        if not (data.ended and index.ended):
            raise OggError("cut_short")
        rate, length = struct.unpack_from("<II", data.packets[0], len(MAGIC))
        payload = b"".join(data.packets[1:])
        ends = packet_ends(data)[1:]
        listed = list(struct.unpack(f"<{len(ends)}Q", index.packets[1])) if len(index.packets) == 2 and len(index.packets[1]) == 8 * len(ends) else None
        if len(payload) & 0xFFFFFFFF != length or ends != listed:
            raise OggError("bad_length")
    except (OggError, struct.error) as e:
        return None, "", str(e) if isinstance(e, OggError) else "cut_short"
    return payload, f"streams={len(streams)};pages={sum(s.pages for s in streams)};packets={len(ends)};end_us={ends[-1] * 1_000_000 // rate};middle_us={ends[len(ends) // 2] * 1_000_000 // rate}", "ok"


def encode_media(rows: DataFrame, payload_col: str, media_col: str = "media") -> DataFrame:
    """All columns and the payload's medium; a column of that name is replaced."""
    ship_package(rows.sparkSession)
    rows = rows.drop(media_col) if media_col != payload_col else rows
    at, names = rows.columns.index(payload_col), [*rows.columns, media_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(0, batch.num_rows, 256):
                part = batch.slice(row, 256)
                media = [write_ogg(padded(x)) for x in part.column(at).to_pylist()]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(media, pa.binary())], names)

    from pyspark.sql.types import BinaryType, StructType

    return rows.mapInArrow(run, StructType(rows.schema.fields[:]).add(media_col, BinaryType()))


def decode_media(rows: DataFrame, media_col: str = "media", keep: tuple[str, ...] = ()) -> DataFrame:
    """The kept columns, the medium, and ``payload``, ``feature``, ``status`` read back from its bytes."""
    ship_package(rows.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(0, batch.num_rows, 256):
                part = batch.slice(row, 256)
                found = [read_samples(x) for x in part.column(part.num_columns - 1).to_pylist()]
                new = [pa.array([f[k] for f in found], kind) for k, kind in enumerate((pa.binary(), pa.string(), pa.string()))]
                yield pa.RecordBatch.from_arrays([*part.columns, *new], [*keep, media_col, "payload", "feature", "status"])

    kinds = "".join(f"`{c}` {rows.schema[c].dataType.simpleString()}, " for c in keep)
    return rows.select(*keep, media_col).mapInArrow(run, f"{kinds}`{media_col}` binary, payload binary, feature string, status string")
