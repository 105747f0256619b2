"""Media columns: Matroska files as byte columns, parsed into packet tables.

``mux`` stores a payload of 8-bit PCM samples (one channel, 8,000 a second) in frames of 192 bytes
(24 ms), laced into SimpleBlocks, in clusters with timestamps and cues. ``parse`` reads any
Matroska byte string: variable-length element ids and sizes (unknown sizes of segments and clusters
too), tracks, clusters, SimpleBlocks and BlockGroups with no, Xiph, fixed-size or EBML lacing, and
cues. Packets carry track, timestamp, key flag, lacing kind and byte range in the file.

Every row is worked on by itself: no shuffle, bounded by the largest file of one row. The query writes the
column to the shared folder and reads it back.

Edge cases: null media give no packets; null texts are empty; an empty text is one frame of blanks;
truncated or unknown elements, and laces that don't fit in their block, end the parse with what is whole
(``strict`` raises instead); repeated rows give equal results; empty tables give empty results; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

# Element ids of the Matroska format.
EBML, EBML_DOCTYPE, SEGMENT, INFO, TIMESTAMP_SCALE = 0x1A45DFA3, 0x4282, 0x18538067, 0x1549A966, 0x2AD7B1
TRACKS, TRACK, TRACK_NUMBER, TRACK_UID, TRACK_TYPE, CODEC, DEFAULT_DURATION = 0x1654AE6B, 0xAE, 0xD7, 0x73C5, 0x83, 0x86, 0x23E383
AUDIO, RATE_HZ, CHANNELS, BIT_DEPTH = 0xE1, 0xB5, 0x9F, 0x6264
CLUSTER, CLUSTER_TIME, SIMPLE_BLOCK, BLOCK_GROUP, BLOCK, REFERENCE = 0x1F43B675, 0xE7, 0xA3, 0xA0, 0xA1, 0xFB
CUES, CUE_POINT, CUE_TIME, CUE_PLACE, CUE_TRACK, CUE_CLUSTER = 0x1C53BB6B, 0xBB, 0xB3, 0xB7, 0xF7, 0xF1
NESTED = {EBML, SEGMENT, INFO, TRACKS, TRACK, AUDIO, CLUSTER, BLOCK_GROUP, CUES, CUE_POINT, CUE_PLACE}
TOP = {CLUSTER, CUES, INFO, TRACKS}  # what ends a cluster of unknown size

FRAME, HZ, FRAMES_PER_BLOCK, BLOCKS_PER_CLUSTER = 192, 8000, 64, 16
LACINGS = ("none", "xiph", "fixed", "ebml")


class Packet(NamedTuple):
    track: int
    timestamp_ms: int
    key: bool
    lacing: str
    start: int
    size: int


def _id(number: int) -> bytes:
    return number.to_bytes((number.bit_length() + 7) // 8, "big")


def _size(n: int) -> bytes:
    width = next(w for w in range(1, 9) if n < (1 << (7 * w)) - 1)
    return (n | 1 << (7 * width)).to_bytes(width, "big")


def element(number: int, body: bytes) -> bytes:
    return _id(number) + _size(len(body)) + body


def _uint(number: int, value: int) -> bytes:
    return element(number, value.to_bytes(max(1, (value.bit_length() + 7) // 8), "big"))


def lace(frames: list[bytes], kind: str) -> bytes:
    """Frames of one block behind their lacing header (without track, time and flags)."""
    if kind == "none":
        return frames[0]
    head = bytes([len(frames) - 1])
    sizes = [len(f) for f in frames]
    if kind == "xiph":
        head += b"".join(b"\xff" * (n // 255) + bytes([n % 255]) for n in sizes[:-1])
    elif kind == "ebml":
        head += _size(sizes[0])
        for before, n in zip(sizes, sizes[1:-1], strict=False):
            width = next(w for w in range(1, 9) if abs(n - before) < 1 << (7 * w - 1))
            head += (n - before + (1 << (7 * width - 1)) - 1 | 1 << (7 * width)).to_bytes(width, "big")
    return head + b"".join(frames)


def block(track: int, relative_ms: int, frames: list[bytes], kind: str, key: bool = True) -> bytes:
    flags = (0x80 if key else 0) | LACINGS.index(kind) << 1
    return _size(track) + struct.pack(">hB", relative_ms, flags) + lace(frames, kind)


def mux(payload: bytes) -> bytes:
    """A Matroska file of the payload, whose length is a multiple of FRAME."""
    step_ms = FRAME * 1000 // HZ
    audio = element(AUDIO, element(RATE_HZ, struct.pack(">d", HZ)) + _uint(CHANNELS, 1) + _uint(BIT_DEPTH, 8))
    tracks = element(TRACKS, element(TRACK, _uint(TRACK_NUMBER, 1) + _uint(TRACK_UID, 1) + _uint(TRACK_TYPE, 2) + _uint(DEFAULT_DURATION, step_ms * 1_000_000) + element(CODEC, b"A_PCM/INT/LIT") + audio))
    parts = [element(INFO, _uint(TIMESTAMP_SCALE, 1_000_000)), tracks]
    at, cues = sum(map(len, parts)), b""
    per_block, per_cluster = FRAME * FRAMES_PER_BLOCK, FRAME * FRAMES_PER_BLOCK * BLOCKS_PER_CLUSTER
    for c in range(0, len(payload), per_cluster):
        time = c // FRAME * step_ms
        body = [_uint(CLUSTER_TIME, time)]
        for b in range(c, min(c + per_cluster, len(payload)), per_block):
            piece = payload[b : min(b + per_block, len(payload))]
            n = len(piece) // FRAME  # frames of one size: the fixed lacing header is their number
            head = _size(1) + struct.pack(">hB", b // FRAME * step_ms - time, 0x80 if n == 1 else 0x84)
            body.append(element(SIMPLE_BLOCK, head + (b"" if n == 1 else bytes([n - 1])) + piece))
        cues += element(CUE_POINT, _uint(CUE_TIME, time) + element(CUE_PLACE, _uint(CUE_TRACK, 1) + _uint(CUE_CLUSTER, at)))
        parts.append(element(CLUSTER, b"".join(body)))
        at += len(parts[-1])
    parts.append(element(CUES, cues))
    return element(EBML, element(EBML_DOCTYPE, b"matroska")) + element(SEGMENT, b"".join(parts))


def _vint(data: bytes, at: int, keep_marker: bool) -> tuple[int, int, bool]:
    """Value, next place, and whether all value bits are set (unknown size)."""
    first = data[at]
    if not first:
        raise ValueError(f"no variable-length number at byte {at}")
    width = 9 - first.bit_length()
    if at + width > len(data):
        raise IndexError(at)
    raw = int.from_bytes(data[at : at + width], "big")
    value = raw & ~(1 << (7 * width))
    return (raw if keep_marker else value), at + width, value == (1 << (7 * width)) - 1


def _laced(data: bytes, at: int, end: int, kind: int) -> list[tuple[int, int]]:
    """(start, size) of the frames of a block whose lacing header is at ``at``."""
    if kind == 0:
        return [(at, end - at)]
    n, at = data[at] + 1, at + 1
    sizes: list[int] = []
    if kind == 2:
        sizes = [(end - at) // n] * (n - 1)
    elif kind == 1:
        for _ in range(n - 1):
            size = 0
            while data[at] == 255:
                size, at = size + 255, at + 1
            sizes.append(size + data[at])
            at += 1
    else:
        for i in range(n - 1):
            before = at
            value, at, _ = _vint(data, at, False)
            sizes.append(value if i == 0 else sizes[-1] + value - ((1 << (7 * (at - before) - 1)) - 1))
    if at > end or any(size < 0 for size in sizes) or at + sum(sizes) > end:
        raise ValueError(f"the laced frames at byte {at} don't fit in their block")
    frames = []
    for size in sizes:
        frames.append((at, size))
        at += size
    return [*frames, (at, end - at)]


class Parsed(NamedTuple):
    packets: list[Packet]
    tracks: dict[int, dict]
    cues: list[tuple[int, int, int]]  # time, track, byte place of the cluster in the file
    clusters: list[tuple[int, int]]  # byte place in the file, time


def parse(data: bytes, strict: bool = False) -> Parsed:
    """Packets, tracks, cues and clusters of a Matroska byte string."""
    out = Parsed([], {}, [], [])
    scale, cluster_time, segment = 1_000_000, 0, 0
    track: dict = {}
    cue: dict = {}
    ends = [len(data)]
    names = [0]
    unknown = [False]
    at = 0
    try:
        while at < len(data):
            while at >= ends[-1] and len(ends) > 1:
                ends.pop(), names.pop(), unknown.pop()
            number, body, _ = _vint(data, at, True)
            size, body, open_end = _vint(data, body, False)
            if unknown[-1] and names[-1] == CLUSTER and number in TOP:
                ends.pop(), names.pop(), unknown.pop()
            end = ends[-1] if open_end else body + size
            if end > len(data):
                raise IndexError(end)
            if number in NESTED:
                if number == SEGMENT:
                    segment = body
                elif number == CLUSTER:
                    out.clusters.append((at, 0))
                elif number == TRACK:
                    track = {}
                elif number == CUE_POINT:
                    cue = {}
                elif number == BLOCK_GROUP:
                    inner = _children(data, body, end)
                    for kind, start, stop in inner:
                        if kind == BLOCK:
                            _block(data, start, stop, cluster_time, scale, not any(k == REFERENCE for k, _, _ in inner), out)
                    at = end
                    continue
                ends.append(end), names.append(number), unknown.append(open_end)
                at = body
                continue
            value = data[body:end]
            if number == SIMPLE_BLOCK:
                _block(data, body, end, cluster_time, scale, None, out)
            elif number == TIMESTAMP_SCALE:
                scale = int.from_bytes(value, "big")
            elif number == CLUSTER_TIME:
                cluster_time = int.from_bytes(value, "big")
                out.clusters[-1] = (out.clusters[-1][0], cluster_time * scale // 1_000_000)
            elif number == TRACK_NUMBER:
                track["number"] = int.from_bytes(value, "big")
                out.tracks[track["number"]] = track
            elif number == TRACK_TYPE:
                track["type"] = int.from_bytes(value, "big")
            elif number == DEFAULT_DURATION:
                track["duration_ns"] = int.from_bytes(value, "big")
            elif number == CODEC:
                track["codec"] = value.rstrip(b"\0").decode("ascii", "replace")
            elif number == RATE_HZ:
                track["hz"] = struct.unpack(">d" if len(value) == 8 else ">f", value)[0]
            elif number in (CHANNELS, BIT_DEPTH):
                track["channels" if number == CHANNELS else "bits"] = int.from_bytes(value, "big")
            elif number == CUE_TIME:
                cue["time"] = int.from_bytes(value, "big") * scale // 1_000_000
            elif number == CUE_TRACK:
                cue["track"] = int.from_bytes(value, "big")
            elif number == CUE_CLUSTER:
                out.cues.append((cue.get("time", 0), cue.get("track", 0), segment + int.from_bytes(value, "big")))
            at = end
    except (IndexError, ValueError, struct.error):
        if strict:
            raise ValueError(f"not a whole Matroska file, at byte {at}") from None
    return out


def _children(data: bytes, at: int, end: int) -> list[tuple[int, int, int]]:
    found = []
    while at < end:
        number, body, _ = _vint(data, at, True)
        size, body, _ = _vint(data, body, False)
        found.append((number, body, body + size))
        at = body + size
    return found


def _block(data: bytes, at: int, end: int, time: int, scale: int, key: bool | None, out: Parsed) -> None:
    track, at, _ = _vint(data, at, False)
    relative, flags = struct.unpack(">hB", data[at : at + 3])
    kind = flags >> 1 & 3
    ms = (time + relative) * scale // 1_000_000
    own = bool(flags & 0x80) if key is None else key
    step = out.tracks.get(track, {}).get("duration_ns", 0)  # frames of a lace follow one another by the track's frame time
    out.packets.extend(Packet(track, ms + i * step // 1_000_000, own, LACINGS[kind], start, size) for i, (start, size) in enumerate(_laced(data, at + 3, end, kind)))


def padded(text: bytes) -> bytes:
    """The payload of a text: blanks up to a positive multiple of FRAME."""
    return text.ljust(max(FRAME, -(-len(text) // FRAME) * FRAME), b" ")


def read_back(media: bytes, track: int = 1) -> bytes:
    return b"".join([media[p.start : p.start + p.size] for p in parse(media, strict=True).packets if p.track == track])


def describe(samples: np.ndarray) -> str:
    """Level, spread, range and zero crossings of unsigned 8-bit samples."""
    centred = samples.astype(np.int64) - 128
    crossings = int(np.count_nonzero((centred[1:] >= 0) != (centred[:-1] >= 0)))
    n = len(samples)
    return f"n={n};mean={int(samples.sum(dtype=np.int64)) / n:.4f};energy={int((centred * centred).sum())};min={samples.min()};max={samples.max()};zc={crossings}"


def _mux(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, 256):
            part = batch.slice(at, 256)
            texts = [t.as_py() or b"" for t in part.column(1)]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(map(len, texts), pa.int64()), pa.array([mux(padded(t)) for t in texts], pa.binary())], names=["doc_id", "n_bytes", "media"])


def to_matroska(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_bytes, media) with every whole text as a Matroska file."""
    slim = docs.select(F.col(key).alias("doc_id"), F.col(text).cast("binary").alias("text"))
    kind = dict(slim.dtypes)["doc_id"]
    return slim.mapInArrow(_mux, f"doc_id {kind}, n_bytes long, media binary")


def packet_table(media: DataFrame, key: str = "doc_id") -> DataFrame:
    """(key, packet, track, timestamp_ms, key_frame, lacing, start, size) of a ``media`` column; byte ranges are in the file."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, data in enumerate(batch.column(1)):
                packets = parse(data.as_py() or b"").packets
                columns = list(zip(*packets, strict=True)) or [[]] * 6
                kinds = [pa.int32(), pa.int64(), pa.bool_(), pa.string(), pa.int64(), pa.int64()]
                own = batch.column(0).take(pa.array([i] * len(packets), pa.int64()))
                yield pa.RecordBatch.from_arrays([own, pa.array(range(len(packets)), pa.int64()), *[pa.array(c, k) for c, k in zip(columns, kinds, strict=True)]], names=["id", "packet", "track", "timestamp_ms", "key_frame", "lacing", "start", "size"])

    slim = media.select(F.col(key).alias("id"), F.col("media"))
    kind = dict(slim.dtypes)["id"]
    return slim.mapInArrow(run, f"id {kind}, packet long, track int, timestamp_ms long, key_frame boolean, lacing string, start long, size long").withColumnRenamed("id", key)


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "packets"]
    for batch in batches:
        rows = []
        for data in batch.column(2):
            media = data.as_py()
            found = parse(media, strict=True).packets
            payload = b"".join([media[p.start : p.start + p.size] for p in found])
            rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(media), hashlib.sha256(media).hexdigest(), describe(np.frombuffer(payload, dtype=np.uint8)), len(found)))
        kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *[pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)]], names=names)


def op3_matroska_column(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's text stored as a column of Matroska audio, read back from its packets, and described."""
    media = C.materialize(to_matroska(C.table(spark, sf_dir, "documents")), "media")
    return media.mapInArrow(_digest, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, packets long")
