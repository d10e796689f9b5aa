"""MPEG audio columns: write payloads as Layer III streams, and read any such stream.

Writing: a payload becomes an ID3v2 tag, a frame with a variable-bitrate table and
CRC-protected frames of MPEG-1 Layer III, 48 kHz, mono, whose side information says
"no coded spectrum"; all main data is ancillary data and carries the payload bytes.
Full frames use the top bitrate, the last one the least that holds the rest.

Reading: skip tags, find the first header that the next one confirms, follow frame
lengths, search anew after damage, check the checksums of all three layers, read the table of
either kind and hold it against the frames, and give exact durations (samples over rate) and the byte offset of every frame.

Defined cases: null text is the empty payload; a stream without frames has 0 samples;
repeated rows stay repeated; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
import struct
import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.llm.common import arrow_rows, slices

# Fixed values of the format: kilobits a second by (version 1?, layer) and index, hertz by version and index.
KBPS = {
    (True, 1): (0, 32, 64, 96, 128, 160, 192, 224, 256, 288, 320, 352, 384, 416, 448),
    (True, 2): (0, 32, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320, 384),
    (True, 3): (0, 32, 40, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320),
    (False, 1): (0, 32, 48, 56, 64, 80, 96, 112, 128, 144, 160, 176, 192, 224, 256),
    (False, 2): (0, 8, 16, 24, 32, 40, 48, 56, 64, 80, 96, 112, 128, 144, 160),
    (False, 3): (0, 8, 16, 24, 32, 40, 48, 56, 64, 80, 96, 112, 128, 144, 160),
}
HERTZ = {3: (44100, 48000, 32000), 2: (22050, 24000, 16000), 0: (11025, 12000, 8000)}
CRC_POLYNOMIAL = 0x8005
UNIT = 576


def _crc_table() -> list[int]:
    out = []
    for byte in range(256):
        value = byte << 8
        for _ in range(8):
            value = (value << 1) ^ (CRC_POLYNOMIAL if value & 0x8000 else 0)
        out.append(value & 0xFFFF)
    return out


CRC_TABLE = _crc_table()


def crc16(data: bytes, bits: int | None = None) -> int:
    """CRC of the data, or of its first ``bits`` bits."""
    bits = 8 * len(data) if bits is None else bits
    value = 0xFFFF
    for byte in data[: bits // 8]:
        value = ((value << 8) & 0xFFFF) ^ CRC_TABLE[(value >> 8) ^ byte]
    for i in range(bits % 8):
        bit = (value >> 15) ^ (data[bits // 8] >> (7 - i) & 1)
        value = (value << 1 & 0xFFFF) ^ (CRC_POLYNOMIAL if bit else 0)
    return value


# Fixed values of Layer II: (subbands, bits of their allocation) runs; which run of runs a stream uses.
ALLOCATION = {
    "a": ((11, 4), (12, 3), (4, 2)),
    "b": ((11, 4), (12, 3), (7, 2)),
    "c": ((2, 4), (6, 3)),
    "d": ((2, 4), (10, 3)),
    "low": ((4, 4), (7, 3), (19, 2)),
}


def allocation_bits(h: Header) -> list[int]:
    """Bits that the allocation of each Layer II subband takes."""
    if h.version != 3:
        name = "low"
    else:
        share = h.kbps if h.mono else h.kbps // 2
        if share < 56:
            name = "d" if h.hertz == 32000 else "c"
        else:
            name = "a" if h.hertz == 48000 or share <= 80 else "b"
    return [bits for count, bits in ALLOCATION[name] for _ in range(count)]


def protected_bits(h: Header, body: bytes) -> int:
    """Bits after the checksum that it covers: side information in Layer III, the bit allocation in
    Layer I, that and the scale factor selection of allocated subbands in Layer II."""
    if h.layer == 3:
        return 8 * h.side
    bound = 32 if h.joint is None else 4 * (h.joint + 1)
    channels = 1 if h.mono else 2
    if h.layer == 1:
        return 4 * (32 if h.mono else 2 * min(bound, 32) + 32 - min(bound, 32))
    value, at, chosen = int.from_bytes(body[:48], "big"), 8 * len(body[:48]), 0
    used = 0
    for i, bits in enumerate(allocation_bits(h)):
        for _ in range(channels if i < bound else 1):
            at -= bits
            used += bits
            if at >= 0 and value >> at & (1 << bits) - 1:
                chosen += channels if i >= bound else 1
    return used + 2 * chosen


@dataclass(frozen=True)
class Header:
    version: int  # 3: MPEG-1, 2: MPEG-2, 0: MPEG-2.5
    layer: int
    protected: bool
    kbps: int
    hertz: int
    mono: bool
    length: int
    samples: int
    joint: int | None = None  # mode extension of joint stereo

    @property
    def side(self) -> int:
        if self.layer != 3:
            return 0
        return (17 if self.mono else 32) if self.version == 3 else (9 if self.mono else 17)


def header_at(word: bytes) -> Header | None:
    """The header that four bytes hold, or None. Free-format streams are not frames here."""
    if len(word) < 4 or word[0] != 0xFF or word[1] & 0xE0 != 0xE0:
        return None
    version, layer = word[1] >> 3 & 3, 4 - (word[1] >> 1 & 3)
    rate, hertz = word[2] >> 4, word[2] >> 2 & 3
    if version == 1 or layer == 4 or rate in (0, 15) or hertz == 3:
        return None
    kbps, hz, padding = KBPS[version == 3, layer][rate], HERTZ[version][hertz], word[2] >> 1 & 1
    samples = 384 if layer == 1 else 1152 if layer == 2 or version == 3 else 576
    length = (12000 * kbps // hz + padding) * 4 if layer == 1 else samples // 8 * 1000 * kbps // hz + padding
    return Header(version, layer, not word[1] & 1, kbps, hz, word[3] >> 6 == 3, length, samples, word[3] >> 4 & 3 if word[3] >> 6 == 1 else None)


def synchsafe(value: int) -> bytes:
    return bytes(value >> s & 127 for s in (21, 14, 7, 0))


def from_synchsafe(data: bytes) -> int:
    return data[0] << 21 | data[1] << 14 | data[2] << 7 | data[3]


@dataclass
class Stream:
    tags: dict[str, str] = field(default_factory=dict)
    offsets: list[int] = field(default_factory=list)
    headers: list[Header] = field(default_factory=list)
    crc_good: int = 0
    crc_bad: int = 0
    skipped: int = 0
    table: dict | None = None
    table_at: int = 0  # offset of the frame that holds the table
    end: int = 0  # of the audio
    main: list[bytes] = field(default_factory=list)

    @property
    def samples(self) -> int:
        return sum(h.samples for h in self.headers)


#: Overhead of a protected mono MPEG-1 Layer III frame: header, CRC, side information.
HEAD = 4 + 2 + 17


def _frame_head(index: int) -> bytes:
    """Header, CRC and empty side information for the bitrate of that index."""
    head = bytes((0xFF, 0xFA, index << 4 | 1 << 2, 0xC4))
    side = bytes(17)
    return head + struct.pack(">H", crc16(head[2:] + side)) + side


FRAME_HEADS = [b""] + [_frame_head(i) for i in range(1, 15)]
FRAME_ROOM = [0] + [3 * k - HEAD for k in KBPS[True, 3][1:]]


def _text_frame(name: str, value: str) -> bytes:
    body = b"\x03" + name.encode() + b"\x00" + value.encode()
    return b"TXXX" + synchsafe(len(body)) + b"\x00\x00" + body


def write_stream(payload: bytes, n_bytes: int) -> bytes:
    tag = _text_frame("payload_bytes", str(len(payload))) + _text_frame("n_bytes", str(n_bytes))
    tag = b"ID3\x04\x00\x00" + synchsafe(len(tag)) + tag
    room, parts, at = FRAME_ROOM[14], [], 0
    while at < len(payload):
        part = payload[at : at + room]
        index = 14 if len(part) == room else next(i for i in range(1, 15) if FRAME_ROOM[i] >= len(part))
        parts.append(FRAME_HEADS[index] + part + bytes(FRAME_ROOM[index] - len(part)))
        at += room
    first = 144  # bytes of the table's frame: 48 kbit/s at 48 kHz
    total = first + sum(map(len, parts))
    ends, seen = [], first
    for p in parts:
        ends.append(seen)
        seen += len(p)
    points = bytes(min(255, ends[i * len(parts) // 100] * 256 // total) if parts else 0 for i in range(100))
    table = b"Xing" + struct.pack(">III", 15, len(parts), total) + points + struct.pack(">I", 100)
    head = bytes((0xFF, 0xFB, 3 << 4 | 1 << 2, 0xC4)) + bytes(17) + table
    return tag + head + bytes(first - len(head)) + b"".join(parts)


# Names of old three-letter text frames in the later form, and encodings by their first byte.
RENAMED = {"TT2": "TIT2", "TP1": "TPE1", "TAL": "TALB", "TYE": "TYER", "TRK": "TRCK", "TCO": "TCON", "TXX": "TXXX", "COM": "COMM"}
ENCODINGS = ("latin-1", "utf-16", "utf-16-be", "utf-8")


def without_stuffing(data: bytes) -> bytes:
    """Undoes unsynchronisation: the zero after each byte 255."""
    return data.replace(b"\xff\x00", b"\xff")


def text_values(body: bytes) -> list[str]:
    """The strings of a text frame; the first byte names their encoding."""
    if not body:
        return [""]
    encoding = ENCODINGS[body[0]] if body[0] < 4 else "latin-1"
    text = body[1:].decode(encoding, "replace")
    return [part.lstrip("\ufeff") for part in text.rstrip("\x00").split("\x00")]


def read_tag(data: bytes, at: int) -> tuple[dict[str, str], int]:
    """Text frames of the tag at ``at`` (versions 2.2, 2.3 and 2.4), and where the tag ends."""
    version, flags, size = data[at + 3], data[at + 5], from_synchsafe(data[at + 6 : at + 10])
    body, i, tags = data[at + 10 : at + 10 + size], 0, {}
    if flags & 128 and version < 4:
        body = without_stuffing(body)
    if flags & 64 and version > 2 and len(body) >= 4:  # extended header: its size counts itself in 2.4 alone
        i = from_synchsafe(body[:4]) if version == 4 else 4 + int.from_bytes(body[:4], "big")
    name_size, head = (3, 6) if version == 2 else (4, 10)
    while i + head <= len(body) and body[i]:
        name = body[i : i + name_size].decode("latin-1")
        if version == 2:
            n, marks = int.from_bytes(body[i + 3 : i + 6], "big"), 0
        else:
            n, marks = from_synchsafe(body[i + 4 : i + 8]) if version == 4 else int.from_bytes(body[i + 4 : i + 8], "big"), body[i + 9]
        content = body[i + head : i + head + n]
        if version == 4 and (marks & 2 or flags & 128):
            content = without_stuffing(content)
        if version == 4 and marks & 1:  # a length before the content
            content = content[4:]
        name = RENAMED.get(name, name)
        if name[0] == "T" and not (version == 4 and marks & 12):  # neither compressed nor encrypted
            values = text_values(content)
            if name == "TXXX":
                tags[values[0]] = values[1] if len(values) > 1 else ""
            else:
                tags[name] = values[0]
        i += head + n
    return tags, at + 10 + size + (10 if version == 4 and flags & 16 else 0)


def read_table(data: bytes, at: int, h: Header) -> dict | None:
    """The variable-bitrate table of the frame at ``at``: either kind, or None."""
    mark = at + 4 + 2 * h.protected + h.side
    kind = data[mark : mark + 4]
    if kind in (b"Xing", b"Info"):
        flags, t, out = int.from_bytes(data[mark + 4 : mark + 8], "big"), mark + 8, {"kind": kind.decode(), "variable": kind == b"Xing"}
        for bit, name in ((1, "frames"), (2, "bytes")):
            if flags & bit:
                out[name], t = int.from_bytes(data[t : t + 4], "big"), t + 4
        return out | {"points": tuple(data[t : t + 100]) if flags & 4 else ()}
    mark = at + 36
    if data[mark : mark + 4] != b"VBRI" or h.length < 62:
        return None
    total, frames, entries, scale, width, per = struct.unpack(">IIHHHH", data[mark + 10 : mark + 26])
    sizes = tuple(scale * int.from_bytes(data[mark + 26 + width * i : mark + 26 + width * (i + 1)], "big") for i in range(entries))
    return {"kind": "VBRI", "variable": True, "frames": frames, "bytes": total, "points": (), "sizes": sizes, "frames_per_entry": per}


def table_faults(got: Stream) -> list[str]:
    """What the table says that the frames do not bear out."""
    t, out = got.table, []
    if t is None:
        return ["missing"]
    whole = got.end - got.table_at
    if t.get("frames", len(got.offsets)) != len(got.offsets):
        out.append("frames")
    if t.get("bytes", whole) != whole:
        out.append("bytes")
    ends = got.offsets + [got.end]
    if t["points"] and got.offsets:  # the byte share reached at each hundredth of the duration, in 256ths
        real = [(ends[i * len(got.offsets) // 100] - got.table_at) * 256 / max(1, whole) for i in range(100)]
        if any(abs(p - min(255, r)) > 1 for p, r in zip(t["points"], real, strict=True)):
            out.append("points")
    if t.get("sizes"):
        starts = [min(i * t["frames_per_entry"], len(got.offsets)) for i in range(len(t["sizes"]) + 1)]
        real = [ends[b] - ends[a] for a, b in zip(starts, starts[1:], strict=False)]
        if list(t["sizes"]) != real:
            out.append("sizes")
    return out


def read_stream(data: bytes) -> Stream:
    out, at, end = Stream(), 0, len(data)
    while data[at : at + 3] == b"ID3" and end - at >= 10:
        tags, at = read_tag(data, at)
        out.tags |= tags
    if end - at >= 128 and data[end - 128 : end - 125] == b"TAG":
        out.tags.setdefault("title", data[end - 125 : end - 95].rstrip(b"\x00 ").decode("latin-1"))
        end -= 128
    out.end = end
    locked: Header | None = None
    known: dict[bytes, Header | None] = {}
    sums: dict[tuple[bytes, int], int] = {}

    def head(i: int) -> Header | None:
        word = data[i : i + 4]
        if word not in known:
            known[word] = header_at(word)
        return known[word]

    while at + 4 <= end:
        h = head(at)
        alike = h and (locked is None or (h.version, h.layer, h.hertz) == (locked.version, locked.layer, locked.hertz))
        if alike and locked is None and at + h.length + 4 <= end:  # not in step yet: the next header must confirm
            after = head(at + h.length)
            alike = after and (after.version, after.layer, after.hertz) == (h.version, h.layer, h.hertz)
        if not alike or at + h.length > end:
            found = data.find(b"\xff", at + 1, end)
            found = end if found < 0 else found
            out.skipped += found - at
            at, locked = found, None
            continue
        locked = h
        side = at + 4 + 2 * h.protected
        if h.protected:
            bits = protected_bits(h, data[side : at + h.length])
            covered = data[at + 2 : at + 4] + data[side : side + -(-bits // 8)]
            if (covered, bits) not in sums:
                sums[covered, bits] = crc16(covered, 16 + bits)
            good = sums[covered, bits] == int.from_bytes(data[at + 4 : at + 6], "big")
            out.crc_good += good
            out.crc_bad += not good
        table = read_table(data, at, h) if out.table is None and not out.offsets and h.layer == 3 else None
        if table:
            out.table, out.table_at = table, at
        else:
            out.offsets.append(at)
            out.headers.append(h)
            out.main.append(data[side + h.side : at + h.length])
        at += h.length
    return out


def payload_of(text: bytes) -> bytes:
    """Bytes 255 up to a positive multiple of the unit."""
    return text + b"\xff" * (max(UNIT, -(-len(text) // UNIT) * UNIT) - len(text))


def signal(payload: bytes) -> str:
    """Statistics of the stored bytes as unsigned samples: mean, deviation, entropy in bits, crossings of the middle."""
    x = np.frombuffer(payload, np.uint8)
    counts = np.bincount(x, minlength=256)
    share = counts[counts > 0] / max(1, len(x))
    above = x >= 128
    values = np.arange(256)
    mean = float(counts @ values) / max(1, len(x))
    deviation = math.sqrt(max(0.0, float(counts @ (values * values)) / max(1, len(x)) - mean * mean))
    return f"mean {mean:.4f};deviation {deviation:.4f};entropy {-(share * np.log2(share)).sum():.4f};crossings {np.count_nonzero(above[1:] != above[:-1])}"


SCHEMA = (
    "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, "
    "frames long, samples long, sample_rate long, crc_good long, table_agrees boolean, frame_offsets array<int>"
)


def _columns():
    names = [c.split()[0] for c in SCHEMA.split(", ")]
    kinds = {"string": pa.string(), "long": pa.int64(), "boolean": pa.bool_(), "array<int>": pa.list_(pa.int32())}
    schema = pa.schema([(n, kinds[c.split()[1]]) for n, c in zip(names, SCHEMA.split(", "), strict=True)])

    def each(batch: pa.RecordBatch):
        for part in slices(batch):
            rows = []
            for doc_id, raw in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                raw = raw or b""
                media = write_stream(payload_of(raw), len(raw))
                got = read_stream(media)
                payload = b"".join(got.main)[: int(got.tags["payload_bytes"])]
                digest = hashlib.sha256(payload).hexdigest()
                rate = got.headers[0].hertz if got.headers else 0
                kbps = sum(h.kbps for h in got.headers) / max(1, len(got.headers))
                agrees = not table_faults(got) and got.crc_bad == 0 and got.skipped == 0
                feature = f"mpeg1-layer3;{rate} Hz;{len(got.offsets)} frames;{got.samples} samples;{kbps:.3f} kbit/s;crc {got.crc_good}/{len(got.offsets)};{signal(payload)}"
                rows.append((doc_id, int(got.tags["n_bytes"]), len(payload), digest, zlib.crc32(payload[-32:]), len(media), hashlib.sha256(media).hexdigest(), feature, len(got.offsets), got.samples, rate, got.crc_good, agrees, got.offsets))
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

    return each


def media_columns(documents: DataFrame) -> DataFrame:
    """(doc_id, text) -> the stored stream's digests, exact duration and seek offsets; map-only."""
    raw = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").cast("binary").alias("raw"))
    return arrow_rows(raw, _columns, SCHEMA)
