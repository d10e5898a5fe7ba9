"""Media columns: MPEG audio streams written and parsed inside a DataFrame.

``parse`` walks a stream of any MPEG version 1, 2 or 2.5 and layer I, II or III: it reads ID3 tags, finds frame headers, resynchronises
over foreign bytes, reads Xing, Info and VBRI tables with their seek tables, verifies the checksums of protected frames, and
gives the exact duration and the byte offset of every frame. The first header, one after foreign bytes, and one of another
version, layer or sampling rate than the stream's count only where a like frame follows or the stream ends. A free-format
frame (no bit rate in its header) is as long as the way to the next two headers like it. Runs of equal frames are
checked together as arrays.

``carry`` stores bytes losslessly in a playable stream: silent mono layer III frames of 240 bytes (48 kHz, 80 kbit/s) whose
ancillary data hold 192 payload bytes each, behind an ID3 tag with the payload's true length and a Xing table.

``streams`` turns a media column into columns of durations, tables and seek offsets; ``describe`` adds digests of the payload.

Defined results: a null text counts as empty, and an empty payload is padded to one frame; a media value that is null,
empty or without any frame parses to zero frames; of a stream that ``carry`` did not write, frames too short for a
payload hold none, and n_bytes is 0 where no tag tells it; ids may be of any type, null or repeated, and rows are handled one
by one; an empty table gives an empty result; columns of the input pass through ``with_media``, but for one of the
result's name, which is replaced.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

UNIT = 192
FRAME = 240
SIDE = 17
HEAD = bytes([0xFF, 0xFA, 0x64, 0xC0])  # version 1, layer III, checksum, 80 kbit/s, 48 kHz, mono
PAYLOAD_AT = 4 + 2 + SIDE

# Bit rates in kbit/s by header index, for (version 1?, layer), and sampling rates by version.
BIT_RATES = {
    (True, 1): (0, 32, 64, 96, 128, 160, 192, 224, 256, 288, 320, 352, 384, 416, 448),
    (True, 2): (0, 32, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320, 384),
    (True, 3): (0, 32, 40, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320),
    (False, 1): (0, 32, 48, 56, 64, 80, 96, 112, 128, 144, 160, 176, 192, 224, 256),
    (False, 2): (0, 8, 16, 24, 32, 40, 48, 56, 64, 80, 96, 112, 128, 144, 160),
    (False, 3): (0, 8, 16, 24, 32, 40, 48, 56, 64, 80, 96, 112, 128, 144, 160),
}
SAMPLE_RATES = {1.0: (44100, 48000, 32000), 2.0: (22050, 24000, 16000), 2.5: (11025, 12000, 8000)}
VERSIONS = {0: 2.5, 2: 2.0, 3: 1.0}
# Bits of each layer II band's allocation at full and at low sampling rates.
FULL_WIDTHS = (4,) * 11 + (3,) * 12 + (2,) * 7
LOW_RATE_WIDTHS = (4,) * 4 + (3,) * 7 + (2,) * 19
FREE_REACH = 8192


def _crc_table() -> np.ndarray:
    """Checksum steps for the polynomial 0x8005, most significant bit first."""
    out = np.arange(256, dtype=np.uint32) << 8
    for _ in range(8):
        out = np.where(out & 0x8000, (out << 1) ^ 0x8005, out << 1) & 0xFFFF
    return out.astype(np.uint16)


CRC = _crc_table()


def crc16(rows: np.ndarray) -> np.ndarray:
    """Checksum of each row of bytes."""
    crc = np.full(len(rows), 0xFFFF, dtype=np.uint16)
    for col in rows.T:
        crc = (crc << np.uint16(8)) ^ CRC[(crc >> np.uint16(8)) ^ col]
    return crc


@dataclass(frozen=True)
class Header:
    version: float
    layer: int
    protected: bool
    kbps: int
    rate: int
    mode: int  # 0 stereo, 1 joint, 2 dual, 3 mono
    extension: int
    length: int  # 0 where a free-format header leaves it open
    samples: int
    pad: int

    @property
    def channels(self) -> int:
        return 1 if self.mode == 3 else 2

    @property
    def side(self) -> int:
        return (17 if self.mode == 3 else 32) if self.version == 1.0 else (9 if self.mode == 3 else 17)

    @property
    def kind(self) -> tuple:
        return self.version, self.layer, self.rate


def header(b: bytes) -> Header | None:
    """A frame header, or None where these bytes are not one."""
    if len(b) < 4 or b[0] != 0xFF or b[1] & 0xE0 != 0xE0:
        return None
    version, layer = VERSIONS.get(b[1] >> 3 & 3), 4 - (b[1] >> 1 & 3)
    if version is None or layer == 4 or b[2] >> 4 == 15 or b[2] >> 2 & 3 == 3 or b[3] & 3 == 2:
        return None
    kbps, rate, pad = BIT_RATES[version == 1.0, layer][b[2] >> 4], SAMPLE_RATES[version][b[2] >> 2 & 3], b[2] >> 1 & 1
    samples = 384 if layer == 1 else 576 if layer == 3 and version != 1.0 else 1152
    slot = 4 if layer == 1 else 1
    length = (samples // (8 * slot) * 1000 * kbps // rate + pad) * slot if kbps else 0
    return Header(version, layer, not b[1] & 1, kbps, rate, b[3] >> 6, b[3] >> 4 & 3, length, samples, pad * slot)


def _free(data: bytes, at: int, end: int, h: Header) -> Header | None:
    """The header with its length measured: two more headers of its kind must follow at even distance, or one and the stream's end."""
    alike = lambda x: (n := header(data[x : x + 4])) is not None and not n.kbps and n.kind == h.kind and n.mode == h.mode
    x = at + 4
    while 0 <= (x := data.find(b"\xff", x + 1, min(end, at + FREE_REACH))):
        if alike(x):
            base = x - at - h.pad
            after = x + base + header(data[x : x + 4]).pad
            if after == end or after + 4 <= end and alike(after):
                return replace(h, length=base + h.pad, kbps=base * h.rate * 8 // h.samples // 1000)
    return None


def _bit_count(h: Header, body: bytes) -> int | None:
    """How many bits behind the checksum it covers, besides the header's last two bytes; None where that is not known."""
    if h.layer == 3:
        return 8 * h.side
    bound = 4 * (h.extension + 1) if h.mode == 1 else 32
    if h.layer == 1:
        return 4 * (h.channels * bound + 32 - bound)
    each = h.kbps / h.channels
    if h.version != 1.0:
        widths = LOW_RATE_WIDTHS
    elif each <= 48:
        widths = (4,) * 2 + (3,) * (10 if h.rate == 32000 else 6)
    else:
        widths = FULL_WIDTHS[: 27 if h.rate == 48000 or each <= 80 else 30]
    bits = int.from_bytes(body[:48], "big")
    size, at, shared = 8 * len(body[:48]), 0, 0
    for band, width in enumerate(widths):
        for _ in range(h.channels if band < bound else 1):
            at += width
            if at > size:
                return None
            if bits >> (size - at) & ((1 << width) - 1):
                shared += 2 if band < bound else 2 * h.channels
    return at + shared


def _crc_bits(body: bytes, bits: int) -> int:
    """Checksum of the first ``bits`` bits."""
    whole = np.frombuffer(body, np.uint8, bits // 8)
    crc = int(crc16(whole.reshape(1, -1))[0])
    for k in range(bits % 8):
        crc = (crc << 1 ^ (0x8005 if (crc >> 15 ^ body[bits // 8] >> (7 - k)) & 1 else 0)) & 0xFFFF
    return crc


@dataclass
class Stream:
    tags: dict = field(default_factory=dict)
    frames: int = 0
    samples: int = 0
    rate: int = 0
    layer: int = 0
    skipped: int = 0
    resyncs: int = 0
    crc_checked: int = 0
    crc_bad: int = 0
    kbps: set = field(default_factory=set)
    vbr: dict = field(default_factory=dict)
    runs: list = field(default_factory=list)  # (first offset, frame length, frames)
    by_rate: dict = field(default_factory=dict)  # samples by sampling rate

    @property
    def micros(self) -> int:
        """Duration; whole microseconds of each sampling rate's part."""
        return sum(n * 1_000_000 // rate for rate, n in self.by_rate.items())

    def all_offsets(self) -> np.ndarray:
        return np.concatenate([at + size * np.arange(n, dtype=np.int64) for at, size, n in self.runs]) if self.runs else np.zeros(0, np.int64)

    def seek(self, every: int = 50) -> list[int]:
        return self.all_offsets()[::every].tolist()

    def features(self) -> str:
        digest = zlib.crc32(self.all_offsets()[::50].astype("<i8").tobytes())
        return (
            f"layer={self.layer};rate={self.rate};frames={self.frames};samples={self.samples};micros={self.micros};kbps={'/'.join(map(str, sorted(self.kbps)))};"
            f"vbr_frames={self.vbr.get('frames', '')};vbr_bytes={self.vbr.get('bytes', '')};crc={self.crc_checked}-{self.crc_bad};resyncs={self.resyncs};skipped={self.skipped};seek={digest:08x}"
        )


def _syncsafe(b: bytes) -> int:
    return b[0] << 21 | b[1] << 14 | b[2] << 7 | b[3]


def _tags(data: bytes) -> tuple[int, int, dict]:
    """Start and end of the audio, and the text frames of the tags."""
    start, end, tags = 0, len(data), {}
    while data[start : start + 3] == b"ID3" and len(data) >= start + 10:
        major, flags, size = data[start + 3], data[start + 5], _syncsafe(data[start + 6 : start + 10])
        at, stop = start + 10, min(start + 10 + size, end)
        while major in (3, 4) and at + 10 <= stop and data[at : at + 4].strip(b"\0"):
            name, n = data[at : at + 4].decode("latin-1"), _syncsafe(data[at + 4 : at + 8]) if major == 4 else int.from_bytes(data[at + 4 : at + 8], "big")
            body = data[at + 10 : min(at + 10 + n, stop)]
            if name[0] == "T" and body:
                code = {0: "latin-1", 1: "utf-16", 2: "utf-16-be", 3: "utf-8"}.get(body[0], "latin-1")
                parts = body[1:].decode(code, "replace").split("\0")
                tags[f"TXXX:{parts[0]}" if name == "TXXX" else name] = parts[1] if name == "TXXX" and len(parts) > 1 else parts[0]
            at += 10 + n
        start = min(start + 10 + size + 10 * (flags >> 4 & 1), end)
    if end - start >= 128 and data[end - 128 : end - 125] == b"TAG":
        end -= 128
        tags["TIT1"] = data[end + 3 : end + 33].split(b"\0")[0].decode("latin-1").rstrip()
    return start, end, tags


def _table(data: bytes, at: int, h: Header) -> dict:
    """Xing, Info or VBRI table of a frame, if it has one."""
    x = at + 4 + h.side
    for x in (x, x + 2):
        if data[x : x + 4] in (b"Xing", b"Info"):
            flags, p, out = int.from_bytes(data[x + 4 : x + 8], "big"), x + 8, {"kind": data[x : x + 4].decode()}
            for bit, name in ((1, "frames"), (2, "bytes")):
                if flags & bit:
                    out[name] = int.from_bytes(data[p : p + 4], "big")
                    p += 4
            if flags & 4:
                out["toc"] = list(data[p : p + 100])
            return out
    if data[at + 36 : at + 40] == b"VBRI" and len(data) >= at + 62:
        size, frames, entries, scale, width, step = struct.unpack(">IIHHHH", data[at + 46 : at + 62])
        gaps = [scale * int.from_bytes(data[p : p + width], "big") for p in range(at + 62, at + 62 + entries * width, width)] if width else []
        return {"kind": "VBRI", "bytes": size, "frames": frames, "step": step, "toc": np.cumsum([0, *gaps]).tolist()}
    return {}


def _checked(data: bytes, raw: np.ndarray, at: int, n: int, h: Header) -> tuple[int, int]:
    """Checksums of a run of frames: how many were looked at and how many are wrong."""
    if h.layer < 3:
        seen = bad = 0
        for x in range(at, at + n * h.length, h.length):
            body = data[x + 6 : x + h.length]
            bits = _bit_count(h, body)
            if bits is not None and bits <= 8 * len(body):
                seen += 1
                bad += _crc_bits(data[x + 2 : x + 4] + body, 16 + bits) != int.from_bytes(data[x + 4 : x + 6], "big")
        return seen, bad
    if h.length < 6 + h.side:
        return 0, 0
    rows = np.lib.stride_tricks.as_strided(raw[at:], (n, 6 + h.side), (h.length, 1))
    want = rows[:, 4].astype(np.uint16) << 8 | rows[:, 5]
    return n, int((crc16(np.concatenate([rows[:, 2:4], rows[:, 6:]], axis=1)) != want).sum())


def parse(data: bytes | None) -> Stream:
    out = Stream()
    if not data:
        return out
    at, end, out.tags = _tags(data)
    raw, lost, kind = np.frombuffer(data, np.uint8), False, None
    while at + 4 <= end:
        h = header(data[at : at + 4])
        if h is not None and not h.kbps:
            h = _free(data, at, end, h)
        after = at + h.length if h else 0
        good = h is not None and h.length > 4 and after <= end
        if good and (lost or h.kind != kind) and after + 4 <= end:
            follower = header(data[after : after + 4])
            good = follower is not None and follower.kind == h.kind
        if not good:
            found = data.find(b"\xff", at + 1, end)
            step = (found if found >= 0 else end) - at
            out.skipped += step
            out.resyncs += not lost
            lost, at = True, at + step
            continue
        if kind is None:
            out.rate, out.layer = h.rate, h.layer
            if table := _table(data, at, h):
                out.vbr, at, lost, kind = table, after, False, h.kind
                continue
        kind = kind or h.kind
        lost = False
        # All frames that follow at this length with this very header.
        room = (end - at) // h.length
        heads = np.lib.stride_tricks.as_strided(raw[at:], (room, 4), (h.length, 1))
        same = (heads == heads[0]).all(axis=1)
        n = int(room if same.all() else same.argmin())
        if h.protected:
            seen, bad = _checked(data, raw, at, n, h)
            out.crc_checked, out.crc_bad = out.crc_checked + seen, out.crc_bad + bad
        out.runs.append((at, h.length, n))
        out.frames, out.samples = out.frames + n, out.samples + n * h.samples
        out.by_rate[h.rate] = out.by_rate.get(h.rate, 0) + n * h.samples
        out.kbps.add(h.kbps)
        at += n * h.length
    out.skipped += max(0, end - at)
    return out


_FRAME_CRC = int(crc16(np.frombuffer(HEAD[2:] + bytes(SIDE), np.uint8).reshape(1, -1))[0])


def carry(content: bytes) -> bytes:
    """A stream that holds the content, padded with blanks to full frames."""
    payload = content + b" " * (-len(content) % UNIT if content else UNIT)
    n = len(payload) // UNIT
    body = np.zeros((n, FRAME), np.uint8)
    body[:, :4] = np.frombuffer(HEAD, np.uint8)
    body[:, 4:6] = np.frombuffer(struct.pack(">H", _FRAME_CRC), np.uint8)
    body[:, PAYLOAD_AT : PAYLOAD_AT + UNIT] = np.frombuffer(payload, np.uint8).reshape(n, UNIT)
    text = b"\0content bytes\0" + str(len(content)).encode()
    tag = b"TXXX" + struct.pack(">I", len(text)) + b"\0\0" + text
    size = len(tag)
    tag = b"ID3\x03\0\0" + bytes([size >> 21 & 127, size >> 14 & 127, size >> 7 & 127, size & 127]) + tag
    info = bytearray(FRAME)
    info[:4] = bytes([HEAD[0], HEAD[1] | 1, HEAD[2], HEAD[3]])
    toc = bytes(min(255, 256 * i // 100) for i in range(100))
    table = b"Xing" + struct.pack(">III", 7, n, (n + 1) * FRAME) + toc
    info[4 + SIDE : 4 + SIDE + len(table)] = table
    return tag + bytes(info) + body.tobytes()


def payload(data: bytes, stream: Stream | None = None) -> bytes:
    """The bytes under the frames of a carried stream, with their padding; frames too short for it hold none."""
    raw, out = np.frombuffer(data or b"", np.uint8), []
    for at, size, n in (stream or parse(data)).runs:
        if size >= PAYLOAD_AT + UNIT:
            out.append(np.lib.stride_tricks.as_strided(raw[at + PAYLOAD_AT :], (n, UNIT), (size, 1)).tobytes())
    return b"".join(out)


def with_media(df: DataFrame, text: str = "text", out: str = "media", replace: bool = False) -> DataFrame:
    """Append a binary column of streams that carry the texts; ``replace`` drops the text."""
    keep = [c for c in df.columns if not (replace and c == text) and c != out]
    schema = df.select(*[F.col(f"`{c}`") for c in keep]).withColumn(out, F.lit(b"")).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                piece = batch.slice(at, 256)
                media = pa.array([carry(x or b"") for x in piece.column(0).to_pylist()], pa.binary())
                yield pa.RecordBatch.from_arrays([*piece.columns[1:], media], names=[*keep, out])

    return df.select(F.encode(F.col(f"`{text}`"), "UTF-8").alias("_media_text"), *[F.col(f"`{c}`") for c in keep]).mapInArrow(run, schema)


FACTS = "layer int, sample_rate int, n_frames long, n_samples long, micros long, kbps array<int>, vbr_kind string, vbr_frames long, vbr_bytes long, vbr_toc array<long>, crc_checked long, crc_bad long, resyncs long, skipped long, tags map<string,string>, seek array<long>"


def _facts(s: Stream, every: int) -> tuple:
    v = s.vbr
    return s.layer, s.rate, s.frames, s.samples, s.micros, sorted(s.kbps), v.get("kind"), v.get("frames"), v.get("bytes"), v.get("toc"), s.crc_checked, s.crc_bad, s.resyncs, s.skipped, list(s.tags.items()), s.seek(every)


def _mapped(df: DataFrame, id_col: str, media: str, columns: str, one: Callable[[bytes | None], tuple]) -> DataFrame:
    """A row of ``columns`` for each media value, behind its id."""
    kind = df.schema[id_col].dataType.simpleString()
    fields = to_arrow_schema(StructType.fromDDL(columns))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                batch = whole.slice(at, 512)
                rows = [one(x.as_py()) for x in batch.column(1)]
                yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([r[i] for r in rows], f.type) for i, f in enumerate(fields))], names=[id_col, *fields.names])

    return df.select(F.col(f"`{id_col}`"), F.col(f"`{media}`")).mapInArrow(run, f"`{id_col}` {kind}, {columns}")


def streams(df: DataFrame, id_col: str = "doc_id", media: str = "media", every: int = 50) -> DataFrame:
    """What a parse tells, as columns: exact duration, tables, checksums, tags, and the offset of every ``every``-th frame."""
    return _mapped(df, id_col, media, FACTS, lambda data: _facts(parse(data), every))


def describe(df: DataFrame, id_col: str = "doc_id", media: str = "media", every: int = 50) -> DataFrame:
    """Read the stored bytes back: payload digests, the features of the stream, its exact duration and its seek offsets."""

    def one(data: bytes | None) -> tuple:
        s = parse(data)
        held = payload(data, s) if s.frames else b""
        told = s.tags.get("TXXX:content bytes", "")
        return (int(told) if told.isascii() and told.isdigit() else 0), len(held), hashlib.sha256(held).hexdigest(), zlib.crc32(held[-16:]), len(data or b""), hashlib.sha256(data or b"").hexdigest(), s.features(), s.samples, s.micros, s.seek(every)

    return _mapped(df, id_col, media, "n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_samples long, micros long, seek array<long>", one)
