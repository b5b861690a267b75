"""Matroska files in a binary column: a writer of 8-bit PCM tracks, and a parser to packet tables.

A payload becomes one audio track (A_PCM/INT/LIT, 8 bits, mono). Frames of ``FRAME`` bytes are laced
into simple blocks, blocks into clusters, and a cue points at each cluster. The parser walks elements
by their variable-length ids and sizes and undoes all four kinds of lacing (none, Xiph, fixed, EBML).

Defined cases: a null or empty text is stored as 64 bytes of 0; equal payloads give equal files;
repeated rows each give a row; a file that breaks off or lies about a size raises ValueError.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import load, slices

# Element ids of the format.
EBML, VERSION, READ_VERSION, MAX_ID, MAX_SIZE, DOC_TYPE, DOC_VERSION, DOC_READ = 0x1A45DFA3, 0x4286, 0x42F7, 0x42F2, 0x42F3, 0x4282, 0x4287, 0x4285
SEGMENT, INFO, SCALE, MUXER, WRITER = 0x18538067, 0x1549A966, 0x2AD7B1, 0x4D80, 0x5741
TRACKS, ENTRY, NUMBER, UID, KIND, LACED, CODEC, AUDIO, RATE, CHANNELS, DEPTH = 0x1654AE6B, 0xAE, 0xD7, 0x73C5, 0x83, 0x9C, 0x86, 0xE1, 0xB5, 0x9F, 0x6264
CLUSTER, TIME, SIMPLE, GROUP, BLOCK = 0x1F43B675, 0xE7, 0xA3, 0xA0, 0xA1
CUES, POINT, CUE_TIME, POSITIONS, CUE_TRACK, CUE_AT = 0x1C53BB6B, 0xBB, 0xB3, 0xB7, 0xF7, 0xF1
MASTERS = {EBML, SEGMENT, INFO, TRACKS, ENTRY, AUDIO, CLUSTER, GROUP, CUES, POINT, POSITIONS}

HERTZ, FRAME, LACE, BLOCKS = 8000, 512, 8, 16


def size_of(n: int, width: int = 0) -> bytes:
    """A number as a variable-length size; all ones is kept for unknown sizes."""
    width = width or next(w for w in range(1, 9) if n < (1 << 7 * w) - 1)
    return (n | 1 << 7 * width).to_bytes(width, "big")


def element(number: int, body: bytes | int | float | str) -> bytes:
    if isinstance(body, int):
        body = body.to_bytes(max(1, (body.bit_length() + 7) // 8), "big")
    elif isinstance(body, float):
        body = struct.pack(">d", body)
    elif isinstance(body, str):
        body = body.encode()
    return number.to_bytes((number.bit_length() + 7) // 8, "big") + size_of(len(body)) + body


HEAD = element(EBML, b"".join(element(*x) for x in ((VERSION, 1), (READ_VERSION, 1), (MAX_ID, 4), (MAX_SIZE, 8), (DOC_TYPE, "matroska"), (DOC_VERSION, 4), (DOC_READ, 2))))
ABOUT = element(INFO, element(SCALE, 1_000_000) + element(MUXER, "columns") + element(WRITER, "columns")) + element(
    TRACKS, element(ENTRY, b"".join(element(*x) for x in ((NUMBER, 1), (UID, 1), (KIND, 2), (LACED, 1), (CODEC, "A_PCM/INT/LIT"), (AUDIO, element(RATE, float(HERTZ)) + element(CHANNELS, 1) + element(DEPTH, 8))))))


def laced(frames: list[bytes], kind: int) -> bytes:
    """The frames of a block behind their lacing head; kind 0 none, 1 Xiph, 2 fixed, 3 EBML."""
    if kind == 0:
        return frames[0]
    head = bytes([len(frames) - 1])
    sizes = [len(f) for f in frames]
    if kind == 1:
        head += b"".join(b"\xff" * (n // 255) + bytes([n % 255]) for n in sizes[:-1])
    elif kind == 3:
        head += size_of(sizes[0])
        for a, b in zip(sizes[:-2], sizes[1:-1]):
            width = next(w for w in range(1, 9) if abs(b - a) < (1 << 7 * w - 1) - 1)
            head += size_of(b - a + (1 << 7 * width - 1) - 1, width)
    return head + b"".join(frames)


def write_matroska(payload: bytes) -> bytes:
    """One file with the payload as samples of a mono track."""
    body, cues, step = [ABOUT], [], FRAME * LACE * BLOCKS
    at = len(ABOUT)
    for start in range(0, len(payload), step):
        time = start * 1000 // HERTZ
        parts = [element(TIME, time)]
        for first in range(start, min(start + step, len(payload)), FRAME * LACE):
            chunk = payload[first : first + FRAME * LACE]
            frames = [chunk[i : i + FRAME] for i in range(0, len(chunk), FRAME)]
            kind = 0 if len(frames) == 1 else 2 if len(chunk) % FRAME == 0 else 3
            parts.append(element(SIMPLE, size_of(1) + struct.pack(">hB", first * 1000 // HERTZ - time, 0x80 | kind << 1) + laced(frames, kind)))
        cues.append(element(POINT, element(CUE_TIME, time) + element(POSITIONS, element(CUE_TRACK, 1) + element(CUE_AT, at))))
        body.append(element(CLUSTER, b"".join(parts)))
        at += len(body[-1])
    return HEAD + element(SEGMENT, b"".join(body) + element(CUES, b"".join(cues)))


def number_at(data: memoryview, at: int, keep: bool) -> tuple[int, int]:
    """A variable-length number and where it ends; keep: with its length mark, as in ids. -1: unknown size."""
    if at >= len(data) or not data[at]:
        raise ValueError(f"no variable-length number at byte {at}")
    width = 9 - data[at].bit_length()
    if at + width > len(data):
        raise ValueError(f"number at byte {at} breaks off")
    whole = int.from_bytes(data[at : at + width], "big")
    bare = whole ^ 1 << 7 * width
    return (whole if keep else -1 if bare == (1 << 7 * width) - 1 else bare), at + width


def elements(data: memoryview, at: int, end: int) -> Iterator[tuple[int, int, int]]:
    """(id, start of body, end of body) of each element, masters before what they hold."""
    ends = [end]
    while at < end:
        while len(ends) > 1 and at >= ends[-1]:
            ends.pop()
        number, at = number_at(data, at, True)
        size, at = number_at(data, at, False)
        stop = ends[-1] if size < 0 else at + size
        if stop > ends[-1]:
            raise ValueError(f"element {number:x} at byte {at} is longer than what holds it")
        yield number, at, stop
        if number in MASTERS:
            ends.append(stop)
        else:
            at = stop


def frames_of(data: memoryview, at: int, stop: int, kind: int) -> list[tuple[int, int]]:
    """(offset, size) of each frame of a block whose lacing begins at ``at``."""
    if kind == 0:
        return [(at, stop - at)]
    count, at = data[at] + 1, at + 1
    sizes: list[int] = []
    if kind == 2:
        sizes = [(stop - at) // count] * count
    else:
        for k in range(count - 1):
            if kind == 1:
                n = 0
                while data[at] == 255:
                    n, at = n + 255, at + 1
                n, at = n + data[at], at + 1
            else:
                first = at
                n, at = number_at(data, at, False)
                if k:
                    n = sizes[-1] + n - ((1 << 7 * (at - first) - 1) - 1)
            sizes.append(n)
        sizes.append(stop - at - sum(sizes))
    if min(sizes) < 0 or at + sum(sizes) > stop:
        raise ValueError(f"lacing at byte {at} doesn't fit its block")
    out = []
    for n in sizes:
        out.append((at, n))
        at += n
    return out


def parse_matroska(file: bytes) -> dict:
    """tracks, packets (track, timestamp_ns, key, lacing, offset, size) and cues (time, track, offset of the cluster)."""
    data = memoryview(file)
    scale, base, segment, time = 1_000_000, 0, 0, 0
    tracks, packets, cues = [], [], []
    value = lambda a, b: int.from_bytes(data[a:b], "big")
    for number, at, stop in elements(data, 0, len(data)):
        if number == SEGMENT:
            segment = at
        elif number == SCALE:
            scale = value(at, stop)
        elif number == ENTRY:
            tracks.append({"number": 0, "codec": "", "rate": 8000.0, "channels": 1, "depth": 0})
        elif number == NUMBER:
            tracks[-1]["number"] = value(at, stop)
        elif number == CODEC:
            tracks[-1]["codec"] = bytes(data[at:stop]).decode()
        elif number == RATE:
            tracks[-1]["rate"] = struct.unpack(">d" if stop - at == 8 else ">f", data[at:stop])[0]
        elif number == CHANNELS:
            tracks[-1]["channels"] = value(at, stop)
        elif number == DEPTH:
            tracks[-1]["depth"] = value(at, stop)
        elif number == TIME:
            base = value(at, stop)
        elif number in (SIMPLE, BLOCK):
            track, at = number_at(data, at, False)
            shift, flags = struct.unpack(">hB", data[at : at + 3])
            kind, clock = flags >> 1 & 3, (base + shift) * scale
            rate = next((t["rate"] * t["channels"] * max(t["depth"], 8) / 8 for t in tracks if t["number"] == track), 0)
            sent = 0
            for offset, n in frames_of(data, at + 3, stop, kind):
                packets.append((track, clock + (round(sent * 1e9 / rate) if rate else 0), bool(flags & 0x80) or number == BLOCK, kind, offset, n))
                sent += n
        elif number == CUE_TIME:
            time = value(at, stop)
        elif number == CUE_TRACK:
            cues.append([time * scale, value(at, stop), 0])
        elif number == CUE_AT:
            cues[-1][2] = segment + value(at, stop)
    return {"tracks": tracks, "packets": packets, "cues": [tuple(c) for c in cues]}


def media_column(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes of the text, and its file as ``media``."""

    def run(batches):
        for batch in slices(batches):
            texts = [t.encode() for t in batch.column(1).to_pylist()]
            files = [write_matroska(t + bytes(-len(t) % 64 if t else 64)) for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(map(len, texts), pa.int64()), pa.array(files, pa.binary())], ["doc_id", "n_bytes", "media"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, media binary")


def packet_table(media: DataFrame, key: str = "doc_id") -> DataFrame:
    """A row for each frame: key, track, timestamp_ns, keyframe, lacing, byte_offset, byte_size, seekable (first of a cued cluster)."""

    def run(batches):
        for batch in slices(batches, "media"):
            rows = []
            for k, file in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if file:
                    found = parse_matroska(file)
                    starts = {c[0] for c in found["cues"]}
                    rows += [(k, *p, p[1] in starts) for p in found["packets"]]
            names = ["key", "track", "timestamp_ns", "keyframe", "lacing", "byte_offset", "byte_size", "seekable"]
            kinds = [batch.schema.field(0).type, pa.int32(), pa.int64(), pa.bool_(), pa.int32(), pa.int64(), pa.int64(), pa.bool_()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [()] * 8, kinds)], names)

    kind = dict(media.dtypes)[key]
    return media.select(key, "media").mapInArrow(run, f"key {kind}, track int, timestamp_ns long, keyframe boolean, lacing int, byte_offset long, byte_size long, seekable boolean").withColumnRenamed("key", key)


def payload_of(file: bytes) -> bytes:
    return b"".join(file[at : at + n] for _, _, _, _, at, n in parse_matroska(file)["packets"])


def feature_of(samples: np.ndarray) -> str:
    """Sums, range, crossings of the middle and the most frequent sample, all whole numbers."""
    wide = samples.astype(np.int64) - 128
    often = np.bincount(samples, minlength=256)
    return f"n={len(wide)};sum={wide.sum()};energy={(wide * wide).sum()};min={wide.min()};max={wide.max()};crossings={np.count_nonzero((wide[1:] < 0) != (wide[:-1] < 0))};mode={often.argmax()}:{often.max()}"


def media_features(media: DataFrame) -> DataFrame:
    """What the stored bytes hold, read back: the digests and the feature of each file."""

    def run(batches):
        for batch in slices(batches, "media"):
            rows = []
            for file in batch.column(2).to_pylist():
                payload = payload_of(file)
                rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(file), hashlib.sha256(file).hexdigest(), feature_of(np.frombuffer(payload, np.uint8))))
            kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(c, t) for c, t in zip(zip(*rows), kinds))], ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    return media.select("doc_id", "n_bytes", "media").mapInArrow(run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


def op2_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_features(media_column(load(spark, sf_dir, "documents")))
