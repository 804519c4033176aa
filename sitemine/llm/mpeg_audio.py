"""MPEG audio as a media column: write payloads into frames, parse any stream back.

Reading.  ``parse`` walks a byte string as a player would: an ID3v2 tag (with its text
frames), an APEv2 or ID3v1 tag at the end, then frame headers.  Where no header stands it
looks for the next sync word and accepts it only if the header is legal, fits the stream's
version, layer and rate, and the header after it (or the end of the audio) is where this
one says.  It reads Xing / Info and VBRI tables whole (counts, quality, and the seek table
as byte offsets), checks each protected frame's CRC-16 over what its layer protects (side
information, or bit allocation and, in layer II, scale factor selection), adds up samples
for the exact duration, and keeps every frame's offset.  Free-format streams, whose frames
do not tell their length, are taken for junk.

Writing.  ``store`` puts a payload into MPEG-2 Layer III frames of 576 samples at 16 kHz
mono, 144 kbit/s: 648 bytes, of which 576 carry payload (one byte a sample) after header,
CRC and side information; an Info frame with frame count, byte count and seek percentages
leads, and an ID3v2.3 tag states the length of the content.  The main data are carried as
they are (side information declares them empty), so any parser can walk the file and the
bytes come back exactly.

Defined cases: null or empty text is one block of 255s; very long texts become longer
files (a file is built per row, rows a few at a time); equal texts give equal files;
streams without any frame parse to zero frames and no duration; rows, ids and extra
columns are kept as they are.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.llm.common import bounded_batches, fresh_name

BLOCK = 576
#: Frames between entries of the seek table.
SEEK_STEP = 1

# Fixed values of the format: kbit/s by (version is 1, layer) and index, Hz by version and index.
BITRATES = {
    (True, 1): (0, 32, 64, 96, 128, 160, 192, 224, 256, 288, 320, 352, 384, 416, 448),
    (True, 2): (0, 32, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320, 384),
    (True, 3): (0, 32, 40, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320),
    (False, 1): (0, 32, 48, 56, 64, 80, 96, 112, 128, 144, 160, 176, 192, 224, 256),
    (False, 2): (0, 8, 16, 24, 32, 40, 48, 56, 64, 80, 96, 112, 128, 144, 160),
    (False, 3): (0, 8, 16, 24, 32, 40, 48, 56, 64, 80, 96, 112, 128, 144, 160),
}
RATES = {1.0: (44100, 48000, 32000), 2.0: (22050, 24000, 16000), 2.5: (11025, 12000, 8000)}
VERSIONS = {0: 2.5, 2: 2.0, 3: 1.0}
# Fixed values of layer II: bits of a subband's allocation, as runs of (subbands, bits), by table.
ALLOCATION = {
    "27": ((11, 4), (12, 3), (4, 2)),
    "30": ((11, 4), (12, 3), (7, 2)),
    "8": ((2, 4), (6, 3)),
    "12": ((2, 4), (10, 3)),
    "low": ((4, 4), (7, 3), (19, 2)),
}


@dataclass(frozen=True)
class Header:
    version: float
    layer: int
    protected: bool
    kbps: int
    rate: int
    mono: bool
    size: int
    samples: int
    bound: int  # subbands below it have an allocation for each channel (joint stereo shares the rest)

    @property
    def side(self) -> int:
        """Bytes of side information (layer III)."""
        if self.layer != 3:
            return 0
        return (17 if self.mono else 32) if self.version == 1.0 else (9 if self.mono else 17)

    @property
    def stream(self) -> tuple:
        return self.version, self.layer, self.rate


@lru_cache(65536)
def header_of(word: int) -> Header | None:
    """The header in 32 bits, or None where they are none."""
    if word >> 21 != 0x7FF or (version := VERSIONS.get(word >> 19 & 3)) is None:
        return None
    layer, kbit, hz = 4 - (word >> 17 & 3), word >> 12 & 15, word >> 10 & 3
    if layer == 4 or kbit in (0, 15) or hz == 3 or word & 3 == 2:
        return None
    first = version == 1.0
    kbps, rate, padding = BITRATES[first, layer][kbit], RATES[version][hz], word >> 9 & 1
    samples = 384 if layer == 1 else 1152 if layer == 2 or first else 576
    size = (12000 * kbps // rate + padding) * 4 if layer == 1 else samples // 8 * 1000 * kbps // rate + padding
    mode = word >> 6 & 3
    bound = ((word >> 4 & 3) + 1) * 4 if mode == 1 else 32
    return Header(version, layer, not word >> 16 & 1, kbps, rate, mode == 3, size, samples, bound)


@lru_cache(65536)
def crc16(data: bytes) -> int:
    """The format's CRC: polynomial 0x8005, start 0xFFFF, most significant bit first."""
    crc = 0xFFFF
    for byte in data:
        crc ^= byte << 8
        for _ in range(8):
            crc = (crc << 1 ^ 0x8005 if crc & 0x8000 else crc << 1) & 0xFFFF
    return crc


def crc16_bits(lead: bytes, data: bytes, bits: int) -> int:
    """``crc16`` of ``lead`` and the first ``bits`` bits of ``data``."""
    crc = crc16(lead + data[: bits // 8])
    for i in range(bits % 8):
        bit = data[bits // 8] >> (7 - i) & 1
        crc = (crc << 1 ^ (0x8005 if crc >> 15 != bit else 0)) & 0xFFFF
    return crc


def allocation_of(head: Header) -> list[int]:
    """Bits of each subband's allocation in a layer II frame."""
    channels = 1 if head.mono else 2
    if head.version != 1.0:
        name = "low"
    elif (each := head.kbps // channels) < 56:
        name = "12" if head.rate == 32000 else "8"
    else:
        name = "27" if head.rate == 48000 or each <= 80 else "30"
    return [bits for subbands, bits in ALLOCATION[name] for _ in range(subbands)]


def protected_bits(head: Header, body: bytes) -> int:
    """How many bits after the CRC it covers, besides the last two header bytes."""
    if head.layer == 3:
        return 8 * head.side
    channels = 1 if head.mono else 2
    if head.layer == 1:
        return 4 * (head.bound * channels + 32 - head.bound)
    number, at, chosen = int.from_bytes(body, "big"), 0, 0
    for band, width in enumerate(allocation_of(head)):
        for _ in range(channels if band < head.bound else 1):
            value = number >> (8 * len(body) - at - width) & ((1 << width) - 1)
            at += width
            chosen += (value > 0) * (1 if band < head.bound else channels)
    return at + 2 * chosen


@dataclass
class Audio:
    """What a stream holds; offsets are bytes from its start."""

    tags: dict[str, str] = field(default_factory=dict)
    head: Header | None = None
    frames: int = 0
    samples: int = 0
    junk: int = 0
    resyncs: int = 0
    checked: int = 0
    bad_crc: int = 0
    vbr: str = ""
    vbr_frames: int = -1
    vbr_bytes: int = -1
    vbr_quality: int = -1
    vbr_seek: list[int] = field(default_factory=list)
    bitrates: set[int] = field(default_factory=set)
    offsets: np.ndarray = field(default_factory=lambda: np.empty(0, np.int64))

    @property
    def duration(self) -> float:
        return self.samples / self.head.rate if self.head else 0.0

    def seek_table(self, step: int = SEEK_STEP) -> list[int]:
        return self.offsets[::step].tolist()

    def feature(self) -> str:
        """One line of everything measured, the seek table by its digest."""
        kind = f"mpeg{self.head.version:g}-layer{self.head.layer}-{self.head.rate}hz" if self.head else "none"
        seek, told = (zlib.crc32(np.asarray(x, "<i8").tobytes()) for x in (self.offsets[::SEEK_STEP], self.vbr_seek))
        return (
            f"{kind};kbps={','.join(map(str, sorted(self.bitrates)))};frames={self.frames};samples={self.samples};seconds={self.duration:.6f};"
            f"crc={self.checked - self.bad_crc}/{self.checked};junk={self.junk};resyncs={self.resyncs};vbr={self.vbr or '-'}:{self.vbr_frames}:{self.vbr_bytes}:{self.vbr_quality};table={told:08x};seek={seek:08x}"
        )


def _syncsafe(b: bytes) -> int:
    return b[0] << 21 | b[1] << 14 | b[2] << 7 | b[3]


def _text(raw: bytes) -> str:
    if not raw:
        return ""
    coding = {0: "latin-1", 1: "utf-16", 2: "utf-16-be", 3: "utf-8"}.get(raw[0], "latin-1")
    return raw[1:].decode(coding, "replace").strip("\0").replace("\0", "=")


def read_id3v2(data: bytes) -> tuple[dict[str, str], int]:
    """Text frames of a leading tag, and its length (0: no tag)."""
    if data[:3] != b"ID3" or len(data) < 10 or data[3] not in (2, 3, 4) or max(data[6:10]) > 127:
        return {}, 0
    version, flags, end = data[3], data[5], 10 + _syncsafe(data[6:10])
    at, tags, wide = 10, {}, 3 if version == 2 else 4
    if flags & 0x40 and version > 2:
        at += _syncsafe(data[10:14]) if version == 4 else 4 + int.from_bytes(data[10:14], "big")
    while at + 2 * wide + 2 <= end and data[at : at + 1].strip(b"\0"):
        name = data[at : at + wide].decode("latin-1")
        raw = data[at + wide : at + 2 * wide]
        size = _syncsafe(raw) if version == 4 else int.from_bytes(raw, "big")
        at += 6 if version == 2 else 10
        if name.startswith("T"):
            tags[name] = _text(data[at : at + size])
        at += size
    return tags, min(len(data), end + (10 if flags & 0x10 else 0))


def _read_tail(data: bytes, tags: dict[str, str], tagged: bool) -> int:
    """Where the audio ends: ID3v1 and APEv2 tags behind it are read."""
    end = len(data)
    if tagged:
        end -= 128
        for name, a, b in (("id3v1.title", 3, 33), ("id3v1.artist", 33, 63), ("id3v1.album", 63, 93), ("id3v1.year", 93, 97)):
            if value := data[end + a : end + b].split(b"\0")[0].decode("latin-1").strip():
                tags[name] = value
    if end >= 32 and data[end - 32 : end - 24] == b"APETAGEX":
        size, count, flags = struct.unpack("<III", data[end - 20 : end - 8])
        start = end - size - (32 if flags & 1 << 31 else 0)
        if 0 <= start <= end - 32:
            at = end - size
            for _ in range(count):
                if at + 8 >= end - 32:
                    break
                length = struct.unpack("<I", data[at : at + 4])[0]
                stop = data.find(b"\0", at + 8, end)
                if stop < 0:
                    break
                tags["ape." + data[at + 8 : stop].decode("latin-1")] = data[stop + 1 : stop + 1 + length].decode("utf-8", "replace")
                at = stop + 1 + length
            end = start
    return end


def _vbr(audio: Audio, frame: bytes, head: Header) -> bool:
    """Whether the frame is a table of variable bitrates instead of sound."""
    at = 4 + head.side
    number = lambda size: int.from_bytes(frame[at : at + size], "big")
    for skip in (0, 2):  # some writers leave room for a CRC, some don't
        if frame[at + skip : at + skip + 4] in (b"Xing", b"Info"):
            at += skip
            audio.vbr = frame[at : at + 4].decode()
            at += 4
            flags = number(4)
            at += 4
            if flags & 1:
                audio.vbr_frames = number(4)
                at += 4
            if flags & 2:
                audio.vbr_bytes = number(4)
                at += 4
            if flags & 4:  # for each hundredth of the time, the 256th of the bytes
                audio.vbr_seek = [part * max(0, audio.vbr_bytes) // 256 for part in frame[at : at + 100]]
                at += 100
            if flags & 8:
                audio.vbr_quality = number(4)
            return True
    if frame[36:40] == b"VBRI":
        audio.vbr, audio.vbr_quality, audio.vbr_bytes, audio.vbr_frames = "VBRI", *struct.unpack(">HII", frame[44:54].ljust(10, b"\0"))
        entries, scale, width, _ = struct.unpack(">HHHH", frame[54:62].ljust(8, b"\0"))
        table = frame[62 : 62 + entries * width]
        audio.vbr_seek = np.cumsum([int.from_bytes(table[i : i + width], "big") * scale for i in range(0, len(table), max(1, width))], dtype=np.int64).tolist()
        return True
    return False


def parse(data: bytes) -> Audio:
    """Everything measurable of an MPEG audio stream; damage is counted, not fatal."""
    tagged = len(data) >= 128 and data[-128:-125] == b"TAG"
    if tagged:
        audio, ended = _walk(data, False)
        if ended:  # these bytes belong to the last frame
            return audio
    return _walk(data, tagged)[0]


def _walk(data: bytes, tagged: bool) -> tuple[Audio, bool]:
    """What the stream holds, with or without an ID3v1 tag behind it, and whether a frame ends where the audio does."""
    audio = Audio()
    audio.tags, at = read_id3v2(data)
    end = _read_tail(data, audio.tags, tagged)
    offsets: list[int] = []
    sure = False  # whether the byte at hand follows a frame that ended there
    while at + 4 <= end:
        head = header_of(int.from_bytes(data[at : at + 4], "big"))
        fits = head is not None and at + head.size <= end and (audio.head is None or head.stream == audio.head.stream)
        if fits and not sure and at + head.size + 4 <= end:
            after = header_of(int.from_bytes(data[at + head.size : at + head.size + 4], "big"))
            fits = after is not None and after.stream == head.stream
        if not fits:
            found = data.find(b"\xff", at + 1, end)
            stop = found if found >= 0 else end
            audio.resyncs += sure
            audio.junk += stop - at
            at, sure = stop, False
            continue
        if head.protected:
            frame = data[at : at + min(head.size, 200)]
            audio.checked += 1
            audio.bad_crc += crc16_bits(frame[2:4], frame[6:], protected_bits(head, frame[6:])) != int.from_bytes(frame[4:6], "big")
        if audio.head is None:
            audio.head = head
            if head.layer == 3 and _vbr(audio, data[at : at + head.size], head):
                at, sure = at + head.size, True
                continue
        offsets.append(at)
        audio.samples += head.samples
        audio.bitrates.add(head.kbps)
        at, sure = at + head.size, True
    audio.junk += end - at
    audio.frames, audio.offsets = len(offsets), np.array(offsets, np.int64)
    return audio, sure and at == end


# The writer's frame: MPEG-2 Layer III with CRC, 144 kbit/s, 16 kHz, mono.
_WORD = 0xFFF2D8C0
_HEAD = header_of(_WORD)
_LEAD = _WORD.to_bytes(4, "big") + crc16(_WORD.to_bytes(4, "big")[2:] + bytes(9)).to_bytes(2, "big") + bytes(9)


def pad(payload: bytes) -> bytes:
    """``payload`` with bytes 255 up to a positive multiple of a block."""
    return payload + b"\xff" * (-len(payload) % BLOCK or (0 if payload else BLOCK))


def _frame_tag(name: bytes, text: bytes) -> bytes:
    return name + struct.pack(">I", len(text) + 1) + b"\0\0\0" + text


def store(content: bytes) -> bytes:
    """An MPEG audio file whose main data are ``content``, padded."""
    payload = pad(content)
    n = len(payload) // BLOCK
    body = np.zeros((n + 1, _HEAD.size), np.uint8)
    body[:, : len(_LEAD)] = np.frombuffer(_LEAD, np.uint8)
    body[1:, len(_LEAD) : len(_LEAD) + BLOCK] = np.frombuffer(payload, np.uint8).reshape(n, BLOCK)
    percent = bytes(256 * i // 100 for i in range(100))
    info = b"Info" + struct.pack(">III", 7, n, body.size) + percent
    body[0, len(_LEAD) : len(_LEAD) + len(info)] = np.frombuffer(info, np.uint8)
    frames = _frame_tag(b"TLEN", str(n * BLOCK * 1000 // _HEAD.rate).encode()) + _frame_tag(b"TXXX", b"content_bytes\0" + str(len(content)).encode())
    size = len(frames)
    tag = b"ID3\x03\0\0" + bytes([size >> 21 & 127, size >> 14 & 127, size >> 7 & 127, size & 127]) + frames
    return tag + body.tobytes()


def payload_of(data: bytes, audio: Audio) -> bytes:
    """The main data of the frames of a file that ``store`` wrote."""
    if not audio.frames:
        return b""
    raw = np.frombuffer(data, np.uint8)
    start = audio.offsets + len(_LEAD)
    if (np.diff(audio.offsets) == _HEAD.size).all():
        return raw[audio.offsets[0] : audio.offsets[0] + audio.frames * _HEAD.size].reshape(audio.frames, -1)[:, len(_LEAD) : len(_LEAD) + BLOCK].tobytes()
    return b"".join(data[s : s + BLOCK] for s in start)


def _rows(batches: Iterator[pa.RecordBatch], row, names: list[str]) -> Iterator[pa.RecordBatch]:
    """Batches with columns ``names`` appended; ``row`` maps the last column's value to them."""
    for batch in batches:
        for part in (batch.slice(i, 64) for i in range(0, batch.num_rows, 64)):
            made = [row(v) for v in part.column(part.num_columns - 1).to_pylist()]
            kept = list(part.columns[:-1])
            new = [pa.array([m[i] for m in made]) for i in range(len(names))]
            yield pa.RecordBatch.from_arrays(kept + new, names=list(part.schema.names[:-1]) + names)


def add_audio(docs: DataFrame, *, text: str = "text", media: str = "media") -> DataFrame:
    """``docs`` with the MPEG audio file of each text as a binary column, in the text's place."""
    keep = [c for c in docs.columns if c != text]
    rows = bounded_batches(docs).select(*keep, F.col(text).cast("binary").alias(media))
    return rows.mapInArrow(lambda batches: _rows(batches, lambda v: (store(v or b""),), [media]), rows.schema)


MEASURES = {
    "feature": "string", "content_bytes": "long", "frames": "long", "samples": "long", "sample_rate": "long", "seconds": "double", "bad_crc": "long",
    "junk_bytes": "long", "seek_offsets": "array<long>", "payload": "binary", "media_bytes": "long", "media_sha256": "string",
}


def measure_row(data: bytes | None) -> tuple:
    data = data or b""
    audio = parse(data)
    stated = audio.tags.get("TXXX", "").rpartition("content_bytes=")[2]
    return (
        audio.feature(), int(stated) if stated.isdigit() else -1, audio.frames, audio.samples, audio.head.rate if audio.head else 0, audio.duration, audio.bad_crc,
        audio.junk, audio.seek_table(), payload_of(data, audio), len(data), hashlib.sha256(data).hexdigest(),
    )


def measure(files: DataFrame, *, media: str = "media") -> DataFrame:
    """``files`` with the stored bytes read back: features, durations, seek offsets, payload."""
    return _measured(files, media, measure_row)


def store_and_measure(docs: DataFrame, *, text: str = "text") -> DataFrame:
    """``measure(add_audio(docs))`` in one pass: each file is built, read back and let go."""
    return _measured(docs.withColumn(text, F.col(text).cast("binary")), text, lambda content: measure_row(store(content or b"")))


def _measured(files: DataFrame, media: str, row: Callable[[bytes | None], tuple]) -> DataFrame:
    keep = [c for c in bounded_batches(files).columns if c != media]
    names = {k: fresh_name(files.select(*keep), k) for k in MEASURES}
    schema = ", ".join([*(f"`{c}` {t}" for c, t in files.select(*keep).dtypes), *(f"`{names[k]}` {t}" for k, t in MEASURES.items())])
    typed = pa.list_(pa.int64())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for out in _rows(batches, row, list(names.values())):
            yield out.set_column(out.schema.get_field_index(names["seek_offsets"]), names["seek_offsets"], out.column(names["seek_offsets"]).cast(typed))

    return files.select(*keep, media).mapInArrow(run, schema)


def op1_mpeg_audio(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    read = store_and_measure(docs)
    size = F.length("payload").cast("long")
    return read.select(
        "doc_id",
        F.col("content_bytes").alias("n_bytes"),
        size.alias("payload_bytes"),
        F.sha2("payload", 256).alias("payload_sha256"),
        F.crc32(F.expr("substring(payload, -32, 32)")).alias("tail_crc32"),
        "media_bytes",
        "media_sha256",
        "feature",
        "frames",
        "samples",
        "sample_rate",
        "seconds",
        "bad_crc",
        "junk_bytes",
        F.array_join("seek_offsets", ",").alias("seek_offsets"),
    )


# The stored form in hexadecimal digits, built from the text by string functions alone.
_LEAD_HEX = "FFF2D8C0" + f"{crc16(bytes.fromhex('D8C0') + bytes(9)):04X}" + "00" * 9
_PERCENT_HEX = "".join(f"{256 * i // 100:02X}" for i in range(100))


def _crc_sql(column: str) -> str:
    """DuckDB: the CRC-32 of a list of bytes, half a byte at a time."""
    halves = []
    for n in range(16):
        for _ in range(4):
            n = n >> 1 ^ (0xEDB88320 if n & 1 else 0)
        halves.append(n)
    half = f"(list_value({', '.join(map(str, halves))}))"
    one = f"xor(xor(a, x) >> 4, {half}[(xor(a, x) & 15) + 1])"
    return f"xor(list_reduce(list_prepend(4294967295, {column}), lambda a, x: xor({one} >> 4, {half}[({one} & 15) + 1])), 4294967295)"


ORACLE = f"""
with t as (select doc_id, coalesce(text, '') as text, octet_length(encode(coalesce(text, '')))::bigint as n_bytes from documents),
p as (select *, hex(encode(text)) || repeat('FF', (case when n_bytes = 0 then 576 else (576 - n_bytes % 576) % 576 end)::bigint) as payload from t),
f as (select *, (length(payload) / 2)::bigint as payload_bytes, (length(payload) / 1152)::bigint as frames from p),
x as (select *, 'TLEN' as k1, (frames * 576 * 1000 // 16000)::varchar as v1, 'content_bytes' as k2, n_bytes::varchar as v2 from f),
y as (select *, hex('TLEN') || printf('%08X', length(v1) + 1) || '000000' || hex(v1)
    || hex('TXXX') || printf('%08X', length(v2) + 15) || '000000' || hex('content_bytes') || '00' || hex(v2) as tags from x),
z as (select *, (length(tags) / 2)::bigint as tag_bytes from y),
m as (select *, hex('ID3') || '030000' || printf('%02X%02X%02X%02X', tag_bytes >> 21 & 127, tag_bytes >> 14 & 127, tag_bytes >> 7 & 127, tag_bytes & 127) || tags
    || '{_LEAD_HEX}' || hex('Info') || '00000007' || printf('%08X', frames) || printf('%08X', (frames + 1) * 648) || '{_PERCENT_HEX}' || repeat('00', {648 - 15 - 116})
    || array_to_string(list_transform(range(frames), lambda i: '{_LEAD_HEX}' || substr(payload, 1152 * i + 1, 1152) || '{"00" * 57}'), '') as media from z),
b as (select *, list_transform(range(8 * frames), lambda i: ((10 + tag_bytes + 648 * (i // 8 + 1)) >> (8 * (i % 8))) & 255) as seek_bytes,
    list_transform(range(800), lambda i: (((256 * (i // 8) // 100) * ((frames + 1) * 648) // 256) >> (8 * (i % 8))) & 255) as told_bytes,
    right(payload, 64) as tail_hex from m),
d as (select *, list_transform(range(32), lambda i: ('0x' || substr(tail_hex, 2 * i + 1, 2))::bigint) as tail from b),
c as (select *, {_crc_sql("seek_bytes")} as seek_crc, {_crc_sql("told_bytes")} as told_crc, {_crc_sql("tail")} as tail_crc32 from d)
select doc_id, n_bytes, payload_bytes, sha256(unhex(payload)) as payload_sha256, tail_crc32::bigint as tail_crc32, (length(media) / 2)::bigint as media_bytes, sha256(unhex(media)) as media_sha256,
    'mpeg2-layer3-16000hz;kbps=144;frames=' || frames || ';samples=' || (frames * 576) || ';seconds=' || printf('%.6f', frames * 576 / 16000.0::double)
    || ';crc=' || (frames + 1) || '/' || (frames + 1) || ';junk=0;resyncs=0;vbr=Info:' || frames || ':' || ((frames + 1) * 648) || ':-1;table=' || printf('%08x', told_crc::bigint)
    || ';seek=' || printf('%08x', seek_crc::bigint) as feature,
    frames, (frames * 576)::bigint as samples, 16000::bigint as sample_rate, frames * 576 / 16000.0::double as seconds, 0::bigint as bad_crc, 0::bigint as junk_bytes,
    array_to_string(list_transform(range(frames), lambda i: 10 + tag_bytes + 648 * (i + 1)), ',') as seek_offsets
from c
"""
