"""MPEG audio columns: frames that carry a payload, and a reader of tags, tables, checksums and times.

wrap() puts bytes into the data area of MPEG-1 layer III frames (mono, 44.1 kHz, CRC on, silent side
information, so the data is ancillary and a player stays silent), after an ID3v2 tag that holds the
payload's length and CRC and a frame with a variable-bitrate table. Frames run at 320 kbit/s but the last,
which takes the lowest rate that fits. read() works on any byte string: it skips ID3v2 and ID3v1 tags,
finds frames again after damage (a header counts where the next one, or the end, follows it), parses
Xing/Info and VBRI tables, checks layer III CRCs (CRCs of layers I and II are counted as unverified: not intact), and gives the exact duration in samples and the byte
offset of every frame for seeking.

Defined results: null or empty text is a payload of 64 zero bytes; equal payloads give equal streams;
bytes without any frame read as zero frames and an empty payload; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import struct
import zlib
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sheetgraph.llm._shared import Scratch, map_arrow, prepare

# Fixed values of the format: kbit/s by index for (MPEG-1, layers 1 to 3) and (MPEG-2 and 2.5, layer 1; layers 2 and 3)
RATES = {
    (1, 1): (0, 32, 64, 96, 128, 160, 192, 224, 256, 288, 320, 352, 384, 416, 448),
    (1, 2): (0, 32, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320, 384),
    (1, 3): (0, 32, 40, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320),
    (2, 1): (0, 32, 48, 56, 64, 80, 96, 112, 128, 144, 160, 176, 192, 224, 256),
    (2, 2): (0, 8, 16, 24, 32, 40, 48, 56, 64, 80, 96, 112, 128, 144, 160),
}
# sample rates by index for MPEG-1; MPEG-2 has a half, MPEG-2.5 a quarter
SAMPLES = (44100, 48000, 32000)
# end of fixed values

PAD_TO = 64


@dataclass
class Header:
    version: int  # 1, 2, or 3 for 2.5
    layer: int
    crc: bool
    kbps: int
    hz: int
    size: int
    samples: int
    mono: bool

    @property
    def side(self) -> int:
        """Bytes of layer III side information."""
        return (17 if self.mono else 32) if self.version == 1 else (9 if self.mono else 17)


_headers: dict[bytes, Header | None] = {}


def header(four: bytes) -> Header | None:
    """A frame header's fields, None where the four bytes are no header."""
    if four not in _headers:
        if len(_headers) > 100_000:
            _headers.clear()
        _headers[four] = _parse_header(four)
    return _headers[four]


def _parse_header(b: bytes) -> Header | None:
    if len(b) < 4 or b[0] != 0xFF or b[1] & 0xE0 != 0xE0:
        return None
    version = {3: 1, 2: 2, 0: 3}.get(b[1] >> 3 & 3)
    layer = 4 - (b[1] >> 1 & 3)
    rate, hz = b[2] >> 4, b[2] >> 2 & 3
    if version is None or layer == 4 or rate in (0, 15) or hz == 3:
        return None
    kbps = RATES[(1, layer) if version == 1 else (2, min(layer, 2))][rate]
    hz = SAMPLES[hz] >> (version - 1)
    pad = b[2] >> 1 & 1
    if layer == 1:
        size, samples = (12_000 * kbps // hz + pad) * 4, 384
    else:
        samples = 576 if layer == 3 and version > 1 else 1152
        size = samples // 8 * 1000 * kbps // hz + pad
    return Header(version, layer, not b[1] & 1, kbps, hz, size, samples, b[3] >> 6 == 3)


def crc16(data: bytes) -> int:
    """The format's checksum: polynomial 0x8005 from 0xFFFF, high bit first."""
    crc = 0xFFFF
    for byte in data:
        crc ^= byte << 8
        for _ in range(8):
            crc = (crc << 1 ^ 0x8005 if crc & 0x8000 else crc << 1) & 0xFFFF
    return crc


_crcs: dict[bytes, int] = {}


def _crc_of(data: bytes) -> int:
    if data not in _crcs:
        if len(_crcs) > 10_000:
            _crcs.clear()
        _crcs[data] = crc16(data)
    return _crcs[data]


def synchsafe(n: int) -> bytes:
    return bytes(n >> s & 127 for s in (21, 14, 7, 0))


def _frame_start(rate: int) -> bytes:
    head = bytes((0xFF, 0xFA, rate << 4, 0xC0))  # MPEG-1 layer III with CRC, 44.1 kHz, mono
    return head + struct.pack(">H", _crc_of(head[2:4] + bytes(17))) + bytes(17)


STARTS = [b""] + [_frame_start(r) for r in range(1, 15)]
ROOM = [0] + [header(STARTS[r][:4]).size - len(STARTS[r]) for r in range(1, 15)]


def wrap(payload: bytes) -> bytes:
    """The payload as a stream: ID3v2 tag, table frame, data frames."""
    most = ROOM[14]
    frames = []
    for k in range(0, len(payload), most):
        part = payload[k : k + most]
        rate = 14 if len(part) == most else next(r for r in range(1, 15) if ROOM[r] >= len(part))
        frames.append(STARTS[rate] + part + bytes(ROOM[rate] - len(part)))
    body = b"".join(frames)
    table = STARTS[14]
    total = len(table) + most + len(body)
    # equal frames but the last: the table of 100 seek points is linear in the frame number
    points, at = [], len(table) + most
    for p in range(100):
        k = p * len(frames) // 100
        points.append(min(255, (at + k * len(frames[0]) if frames else 0) * 256 // total))
    xing = b"Xing" + struct.pack(">III", 7, len(frames), total) + bytes(points)
    text = b"\x03payload\0" + f"{len(payload)} {zlib.crc32(payload)}".encode()
    tag = b"TXXX" + synchsafe(len(text)) + b"\0\0" + text
    return b"ID3\x04\0\0" + synchsafe(len(tag)) + tag + table + xing + bytes(most - len(xing)) + body


@dataclass
class Stream:
    tags: dict[str, str] = field(default_factory=dict)
    table: str = ""
    table_frames: int | None = None
    table_bytes: int | None = None
    points: list[int] = field(default_factory=list)
    offsets: list[int] = field(default_factory=list)
    sizes: list[int] = field(default_factory=list)
    samples: int = 0
    hz: int = 0
    bad_crcs: int = 0
    unverified: int = 0  # frames with a checksum that is not checked, those of layers I and II
    skipped: int = 0
    parts: list[bytes] = field(default_factory=list)

    @property
    def payload(self) -> bytes:
        body = b"".join(self.parts)
        told = self.tags.get("payload", "").split()
        return body[: int(told[0])] if len(told) == 2 and told[0].isdigit() else body

    @property
    def intact(self) -> bool:
        told = self.tags.get("payload", "").split()
        return not self.bad_crcs and not self.unverified and not self.skipped and (len(told) != 2 or told[1] == str(zlib.crc32(self.payload)))


def _id3v2(data: bytes, out: Stream) -> int:
    """Parses a tag at the start; returns where the audio may begin."""
    if data[:3] != b"ID3" or len(data) < 10:
        return 0
    size = sum((x & 127) << s for x, s in zip(data[6:10], (21, 14, 7, 0)))
    at, end, wide = 10, min(len(data), 10 + size), data[3] < 4
    while at + 10 <= end and data[at : at + 4].strip(b"\0"):
        name = data[at : at + 4].decode("latin-1")
        raw = data[at + 4 : at + 8]
        n = int.from_bytes(raw, "big") if wide else sum((x & 127) << s for x, s in zip(raw, (21, 14, 7, 0)))
        text = data[at + 10 : min(end, at + 10 + n)]
        if name[:1] == "T" and text:
            value = text[1:].decode({0: "latin-1", 1: "utf-16", 2: "utf-16-be"}.get(text[0], "utf-8"), "replace")
            key, _, rest = value.partition("\0") if name == "TXXX" else (name, "", value)
            out.tags[key] = rest.rstrip("\0")
        at += 10 + n
    return 10 + size + (10 if data[5] & 16 else 0)


def _table(data: bytes, at: int, h: Header, out: Stream) -> bool:
    """A frame that holds a variable-bitrate table instead of sound."""
    x = at + 4 + 2 * h.crc + h.side
    if data[x : x + 4] in (b"Xing", b"Info"):
        out.table = data[x : x + 4].decode()
        end = at + h.size  # fields that a cut frame has no room for are not there
        flags = int.from_bytes(data[x + 4 : x + 8], "big") if x + 8 <= end else 0
        x += 8
        flags &= (x + 4 * (flags & 1) <= end) | 2 * (x + 4 * (flags & 1) + 4 <= end) | 4 * (x + 4 * (flags & 1) + 2 * (flags & 2) + 100 <= end)
        if flags & 1:
            (out.table_frames,) = struct.unpack_from(">I", data, x)
            x += 4
        if flags & 2:
            (out.table_bytes,) = struct.unpack_from(">I", data, x)
            x += 4
        if flags & 4:
            out.points = list(data[x : x + 100])
        return True
    x = at + 36  # this table's place is the same for all modes
    if data[x : x + 4] == b"VBRI" and len(data) >= x + 26:
        out.table = "VBRI"
        out.table_bytes, out.table_frames, entries, scale, width = struct.unpack_from(">IIHHH", data, x + 10)
        entries = min(entries, max(0, at + h.size - x - 26) // width if width else 0)
        out.points = [int.from_bytes(data[x + 26 + k * width : x + 26 + (k + 1) * width], "big") * scale for k in range(entries)]
        return True
    return False


def read(data: bytes) -> Stream:
    """Everything that can be told from the bytes of a stream."""
    out = Stream()
    at = _id3v2(data, out)
    end = len(data)
    if end - 128 >= at and data[end - 128 : end - 125] == b"TAG":
        end -= 128
        out.tags.setdefault("TIT2", data[end + 3 : end + 33].rstrip(b"\0 ").decode("latin-1"))
    known = False
    while at + 4 <= end:
        h = header(data[at : at + 4])
        after = at + h.size if h else 0
        if h is None or after > end or not (known or after == end or header(data[after : after + 4])):
            known = False
            nxt = data.find(b"\xff", at + 1, end)
            nxt = end if nxt < 0 else nxt
            out.skipped += nxt - at
            at = nxt
            continue
        known = True
        skip = 4
        if h.crc:
            skip += 2
            if h.layer == 3 and _crc_of(data[at + 2 : at + 4] + data[at + 6 : at + 6 + h.side]) != int.from_bytes(data[at + 4 : at + 6], "big"):
                out.bad_crcs += 1
            out.unverified += h.layer != 3
        if h.layer == 3:
            skip += h.side
        if not out.offsets and not out.table and _table(data, at, h, out):
            out.hz = h.hz
        else:
            out.offsets.append(at)
            out.sizes.append(h.size)
            out.samples += h.samples
            out.hz = out.hz or h.hz
            out.parts.append(data[at + skip : after])
        at = after
    out.skipped += max(0, end - at)
    return out


def encode(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_bytes, media: each text, padded by zero bytes to a positive multiple of 64, as a stream."""
    prepare(docs.sparkSession)

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            bodies = [b"" if x is None else x for x in batch.column(1).to_pylist()]
            media = [wrap(b + bytes(-len(b) % PAD_TO or (0 if b else PAD_TO))) for b in bodies]
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(b) for b in bodies], pa.int64()), pa.array(media, pa.binary())], names=["doc_id", "n_bytes", "media"])

        return step

    src = docs.select(F.col(key).cast("long").alias("doc_id"), F.encode(F.col(text), "UTF-8").alias("body"))
    return map_arrow(src, make, "doc_id long, n_bytes long, media binary")


MEASURES = "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, n_frames int, duration_samples long, sample_rate int, frame_offsets array<int>, intact boolean, feature string"


def measure(media: DataFrame, keep: tuple[str, ...] = ("doc_id", "n_bytes"), column: str = "media") -> DataFrame:
    """The columns in keep and what the stored bytes say: MEASURES."""
    prepare(media.sparkSession)
    names = [*keep, *(x.split()[0] for x in MEASURES.split(", "))]

    def make():
        def one(data: bytes) -> tuple:
            s = read(data)
            body = s.payload
            rate = sum(s.sizes) * 8 * s.hz // (1000 * s.samples) if s.samples else 0
            feature = json.dumps({"frames": len(s.offsets), "samples": s.samples, "hz": s.hz, "kbps": rate, "table": s.table, "table_agrees": s.table_frames == len(s.offsets), "bad_crcs": s.bad_crcs, "unverified": s.unverified, "skipped": s.skipped, "first": s.offsets[0] if s.offsets else None, "middle": s.offsets[len(s.offsets) // 2] if s.offsets else None}, separators=(",", ":"))
            return len(body), hashlib.sha256(body).hexdigest(), zlib.crc32(body[-64:]), len(data), hashlib.sha256(data).hexdigest(), len(s.offsets), s.samples, s.hz, s.offsets, s.intact, feature

        types = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int32(), pa.int64(), pa.int32(), pa.list_(pa.int32()), pa.bool_(), pa.string()]

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            rows = [one(b"" if x is None else x) for x in batch.column(len(keep)).to_pylist()]
            return pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], *(pa.array(c, t) for c, t in zip(zip(*rows), types))], names=names)

        return step

    fields = {f.name: f.dataType.simpleString() for f in media.schema.fields}
    return map_arrow(media.select(*keep, column), make, ", ".join([*(f"`{c}` {fields[c]}" for c in keep), MEASURES]))


def store_and_measure(docs: DataFrame, scratch: Scratch, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Streams stored as a parquet column in the shared folder, then read back and measured."""
    return measure(scratch.keep(encode(docs, key, text)))
