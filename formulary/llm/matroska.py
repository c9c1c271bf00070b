"""Matroska files: a writer, and a parser that gives packet tables.

The parser reads variable-length EBML elements (known and unknown sizes), segment information, tracks, clusters,
simple blocks and block groups with any of the four lacings, and cues. Every packet comes with its track, its
timestamp and its byte range in the file.
"""

from __future__ import annotations

import hashlib
import math
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Element numbers of the public container format.
EBML, SEGMENT, INFO, TRACKS, CLUSTER, CUES, VOID, CRC = 0x1A45DFA3, 0x18538067, 0x1549A966, 0x1654AE6B, 0x1F43B675, 0x1C53BB6B, 0xEC, 0xBF
TIMESTAMP_SCALE, DURATION, MUXER, WRITER = 0x2AD7B1, 0x4489, 0x4D80, 0x5741
TRACK_ENTRY, TRACK_NUMBER, TRACK_UID, TRACK_TYPE, CODEC_ID, LACING_FLAG = 0xAE, 0xD7, 0x73C5, 0x83, 0x86, 0x9C
AUDIO, SAMPLING, CHANNELS, BIT_DEPTH = 0xE1, 0xB5, 0x9F, 0x6264
TIMESTAMP, SIMPLE_BLOCK, BLOCK_GROUP, BLOCK, BLOCK_DURATION = 0xE7, 0xA3, 0xA0, 0xA1, 0x9B
CUE_POINT, CUE_TIME, CUE_POSITIONS, CUE_TRACK, CUE_CLUSTER = 0xBB, 0xB3, 0xB7, 0xF7, 0xF1
_TOP = {INFO, TRACKS, CLUSTER, CUES, SEGMENT, EBML, 0x114D9B74, 0x1941A469, 0x1043A770, 0x1254C367}

RATE = 8000
FRAME = 64
LACED = 8
CLUSTER_MS = 4096


def write_number(n: int, width: int = 0) -> bytes:
    """A size as a variable-length number; the all-ones pattern of a width stands for unknown and is never written."""
    width = width or next(w for w in range(1, 9) if n < (1 << 7 * w) - 1)
    return (n | 1 << 7 * width).to_bytes(width, "big")


def element(number: int, body: bytes) -> bytes:
    return number.to_bytes((number.bit_length() + 7) // 8, "big") + write_number(len(body)) + body


def unsigned(number: int, value: int) -> bytes:
    return element(number, value.to_bytes(max(1, (value.bit_length() + 7) // 8), "big"))


def lace(frames: list[bytes], kind: str) -> tuple[int, bytes]:
    """Flag bits and body of a block with several frames. kind: none, xiph, fixed or ebml."""
    if kind == "none" or len(frames) == 1:
        if len(frames) != 1:
            raise ValueError("a block without lacing has one frame")
        return 0, frames[0]
    head = bytes([len(frames) - 1])
    sizes = [len(f) for f in frames]
    if kind == "fixed":
        if len(set(sizes)) > 1:
            raise ValueError("fixed lacing needs frames of one size")
        return 0x04, head + b"".join(frames)
    if kind == "xiph":
        return 0x02, head + b"".join(b"\xff" * (s // 255) + bytes([s % 255]) for s in sizes[:-1]) + b"".join(frames)
    if kind == "ebml":
        coded = write_number(sizes[0])
        for a, b in zip(sizes, sizes[1:-1]):
            width = next(w for w in range(1, 9) if abs(b - a) < (1 << 7 * w - 1))
            coded += write_number(b - a + (1 << 7 * width - 1) - 1, width)
        return 0x06, head + coded + b"".join(frames)
    raise ValueError(f"unknown lacing {kind}")


def write_pcm(payload: bytes, rate: int = RATE, frame: int = FRAME, laced: int = LACED, cluster_ms: int = CLUSTER_MS) -> bytes:
    """Store bytes as unsigned 8-bit mono samples: blocks of `laced` equal frames (fixed lacing), the last ones with
    EBML lacing where sizes differ; a new cluster when the block time would pass cluster_ms; a cue for each cluster."""
    header = element(EBML, unsigned(0x4286, 1) + unsigned(0x42F7, 1) + unsigned(0x42F2, 4) + unsigned(0x42F3, 8) + element(0x4282, b"matroska") + unsigned(0x4287, 4) + unsigned(0x4285, 2))
    info = element(INFO, unsigned(TIMESTAMP_SCALE, 1_000_000) + element(DURATION, struct.pack(">d", len(payload) * 1000 / rate)) + element(MUXER, b"formulary") + element(WRITER, b"formulary"))
    audio = element(AUDIO, element(SAMPLING, struct.pack(">d", float(rate))) + unsigned(CHANNELS, 1) + unsigned(BIT_DEPTH, 8))
    tracks = element(TRACKS, element(TRACK_ENTRY, unsigned(TRACK_NUMBER, 1) + unsigned(TRACK_UID, 1) + unsigned(TRACK_TYPE, 2) + unsigned(LACING_FLAG, 1) + element(CODEC_ID, b"A_PCM/INT/LIT") + audio))
    body, cues, at, opened = [info, tracks], [], len(info) + len(tracks), None
    blocks: list[bytes] = []

    def close() -> None:
        nonlocal at, blocks
        if opened is not None:
            cluster = element(CLUSTER, unsigned(TIMESTAMP, opened) + b"".join(blocks))
            cues.append(element(CUE_POINT, unsigned(CUE_TIME, opened) + element(CUE_POSITIONS, unsigned(CUE_TRACK, 1) + unsigned(CUE_CLUSTER, at))))
            body.append(cluster)
            at, blocks = at + len(cluster), []

    step = frame * laced
    for i in range(0, len(payload), step):
        part = payload[i : i + step]
        frames = [part[j : j + frame] for j in range(0, len(part), frame)]
        flags, data = lace(frames, "none" if len(frames) == 1 else "fixed" if len(part) % frame == 0 else "ebml")
        ms = i * 1000 // rate
        if opened is None or ms - opened >= cluster_ms:
            close()
            opened = ms
        blocks.append(element(SIMPLE_BLOCK, b"\x81" + struct.pack(">hB", ms - opened, 0x80 | flags) + data))
    close()
    return header + element(SEGMENT, b"".join(body) + element(CUES, b"".join(cues)))


@dataclass
class Media:
    """What a file holds: tracks by number, packets (track, timestamp ns, first byte, length, keyframe), cues (time, track, byte of cluster)."""

    scale: int = 1_000_000
    duration: float | None = None
    tracks: dict[int, dict] = field(default_factory=dict)
    packets: list[tuple[int, int, int, int, bool]] = field(default_factory=list)
    cues: list[tuple[int, int, int]] = field(default_factory=list)
    clusters: int = 0
    truncated: bool = False


class Broken(ValueError):
    """The bytes don't follow the container format."""


def read_id(data: bytes, at: int) -> tuple[int, int]:
    if at >= len(data) or not data[at]:
        raise Broken(f"no element number at byte {at}")
    width = 9 - data[at].bit_length()
    if width > 4 or at + width > len(data):
        raise Broken(f"no element number at byte {at}")
    return int.from_bytes(data[at : at + width], "big"), at + width


def read_number(data: bytes, at: int) -> tuple[int | None, int]:
    """A variable-length number (None: unknown) and the byte after it."""
    if at >= len(data) or not data[at]:
        raise Broken(f"no size at byte {at}")
    width = 9 - data[at].bit_length()
    if at + width > len(data):
        raise Broken(f"no size at byte {at}")
    value = int.from_bytes(data[at : at + width], "big") & ((1 << 7 * width) - 1)
    return (None if value == (1 << 7 * width) - 1 else value), at + width


def _children(data: bytes, at: int, end: int) -> Iterator[tuple[int, int, int]]:
    while at < end:
        number, at = read_id(data, at)
        size, at = read_number(data, at)
        stop = end if size is None else min(at + size, end)
        yield number, at, stop
        at = stop


def _uint(data: bytes, at: int, end: int) -> int:
    return int.from_bytes(data[at:end], "big")


def _float(data: bytes, at: int, end: int) -> float:
    if end - at not in (0, 4, 8):
        raise Broken(f"a float of {end - at} bytes")
    value = struct.unpack(">f" if end - at == 4 else ">d", data[at:end])[0] if end > at else 0.0
    if not math.isfinite(value):
        raise Broken("a float that is no number")
    return value


def frame_ranges(data: bytes, at: int, end: int, lacing: int) -> list[tuple[int, int]]:
    """(first byte, length) of each frame in a block's body."""
    if not lacing:
        return [(at, end - at)]
    if at >= end:
        raise Broken("a laced block without a frame count")
    count, at, sizes = data[at] + 1, at + 1, []
    if lacing == 2:
        if (end - at) % count:
            raise Broken("fixed lacing of uneven frames")
        sizes = [(end - at) // count] * (count - 1)
    elif lacing == 1:
        for _ in range(count - 1):
            size = 0
            while at < end and data[at] == 255:
                size, at = size + 255, at + 1
            if at >= end:
                raise Broken("lacing runs past its block")
            size, at = size + data[at], at + 1
            sizes.append(size)
    elif count > 1:
        first, at = read_number(data, at)
        sizes = [first or 0]
        for _ in range(count - 2):
            start = at
            raw, at = read_number(data, at)
            width = at - start
            raw = (1 << 7 * width) - 1 if raw is None else raw
            sizes.append(sizes[-1] + raw - ((1 << 7 * width - 1) - 1))
    last = end - at - sum(sizes)
    if last < 0 or min(sizes, default=0) < 0:
        raise Broken("lacing runs past its block")
    out = []
    for size in [*sizes, last]:
        out.append((at, size))
        at += size
    return out


def parse(data: bytes) -> Media:
    """Packet table of a file. A cut file gives what is whole and sets truncated; bytes of another format raise Broken."""
    out = Media()
    if data[:4] != EBML.to_bytes(4, "big"):
        raise Broken("not an EBML file")

    def block(at: int, end: int, base: int, key: bool | None, duration: int | None) -> None:
        track, at = read_number(data, at)
        if at + 3 > end:
            raise Broken("a block without a header")
        relative, flags = struct.unpack(">hB", data[at : at + 3])
        ranges = frame_ranges(data, at + 3, end, flags >> 1 & 3)
        t, entry = (base + relative) * out.scale, out.tracks.get(track, {})
        step = entry.get("default_ns") or (duration * out.scale // len(ranges) if duration else 0)
        for first, size in ranges:
            if not step and entry.get("bytes_per_second"):
                stamp, t = t, t + size * 1_000_000_000 // entry["bytes_per_second"]
            else:
                stamp, t = t, t + step
            out.packets.append((track, stamp, first, size, bool(flags & 0x80) if key is None else key))

    def cluster(at: int, end: int, size_known: bool) -> int:
        base = 0
        out.clusters += 1
        while at < end:
            number, body = read_id(data, at)
            if not size_known and number in _TOP:
                return at
            size, body = read_number(data, body)
            stop = end if size is None else body + size
            if stop > end:
                out.truncated = True
                return end
            if number == TIMESTAMP:
                base = _uint(data, body, stop)
            elif number == SIMPLE_BLOCK:
                block(body, stop, base, None, None)
            elif number == BLOCK_GROUP:
                parts = list(_children(data, body, stop))
                duration = next((_uint(data, a, b) for k, a, b in parts if k == BLOCK_DURATION), None)
                for k, a, b in parts:
                    if k == BLOCK:
                        block(a, b, base, all(x[0] != 0xFB for x in parts), duration)
            at = stop
        return at

    def segment(at: int, end: int) -> None:
        start = at
        while at < end:
            number, body = read_id(data, at)
            size, body = read_number(data, body)
            stop = end if size is None else min(body + size, end)
            out.truncated |= size is not None and body + size > end
            if number == INFO:
                for k, a, b in _children(data, body, stop):
                    if k == TIMESTAMP_SCALE:
                        out.scale = _uint(data, a, b)
                    elif k == DURATION:
                        out.duration = _float(data, a, b)
            elif number == TRACKS:
                for k, a, b in _children(data, body, stop):
                    if k == TRACK_ENTRY:
                        entry: dict = {}
                        for k2, a2, b2 in _children(data, a, b):
                            if k2 in (TRACK_NUMBER, TRACK_TYPE):
                                entry["number" if k2 == TRACK_NUMBER else "type"] = _uint(data, a2, b2)
                            elif k2 == CODEC_ID:
                                entry["codec"] = data[a2:b2].decode("ascii", "replace")
                            elif k2 == 0x23E383:
                                entry["default_ns"] = _uint(data, a2, b2)
                            elif k2 == AUDIO:
                                for k3, a3, b3 in _children(data, a2, b2):
                                    if k3 == SAMPLING:
                                        entry["rate"] = _float(data, a3, b3)
                                    elif k3 in (CHANNELS, BIT_DEPTH):
                                        entry["channels" if k3 == CHANNELS else "bits"] = _uint(data, a3, b3)
                        if entry.get("codec", "").startswith("A_PCM") and entry.get("rate"):
                            entry["bytes_per_second"] = int(entry["rate"] * entry.get("channels", 1) * entry.get("bits", 8) // 8)
                        out.tracks[entry.get("number", 0)] = entry
            elif number == CLUSTER:
                stop = cluster(body, stop, size is not None)
            elif number == CUES:
                for k, a, b in _children(data, body, stop):
                    if k == CUE_POINT:
                        parts = list(_children(data, a, b))
                        when = next((_uint(data, x, y) for n, x, y in parts if n == CUE_TIME), 0)
                        for n, x, y in parts:
                            if n == CUE_POSITIONS:
                                pos = {m: _uint(data, u, v) for m, u, v in _children(data, x, y)}
                                out.cues.append((when * out.scale, pos.get(CUE_TRACK, 0), start + pos.get(CUE_CLUSTER, 0)))
            at = stop

    try:
        at = 0
        while at < len(data):
            number, body = read_id(data, at)
            size, body = read_number(data, body)
            stop = len(data) if size is None else min(body + size, len(data))
            out.truncated |= size is not None and body + size > len(data)
            if number == SEGMENT:
                segment(body, stop)
            at = stop
    except Broken:
        if not out.truncated:
            raise
    return out


def read_payload(data: bytes, media: Media, track: int = 1) -> bytes:
    return b"".join([data[at : at + size] for t, _, at, size, _ in media.packets if t == track])


def padded(text: bytes, unit: int = 64) -> bytes:
    """Zero bytes up to a positive multiple of the unit."""
    return text + bytes(max(unit, -(-len(text) // unit) * unit) - len(text))


def packet_table(files: DataFrame, id_col: str, media_col: str) -> DataFrame:
    """Packets of each file: id, track, codec, packet, timestamp_ns, first_byte, n_bytes, keyframe, status.

    Null files and bytes of another format give one row with a status and no packet; cut files give their whole packets.
    """

    schema = pa.schema([("id", pa.int64()), ("track", pa.int64()), ("codec", pa.string()), ("packet", pa.int64()), ("timestamp_ns", pa.int64()), ("first_byte", pa.int64()), ("n_bytes", pa.int64()), ("keyframe", pa.bool_()), ("status", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for key, raw in zip(batch.column(0).to_pylist(), batch.column(1)):
                raw = raw.as_py()
                try:
                    m = parse(raw) if raw is not None else Media()
                    status = "null" if raw is None else "truncated" if m.truncated else "ok"
                except Broken as e:
                    m, status = Media(), f"broken: {e}"
                rows = [(key, t, m.tracks.get(t, {}).get("codec"), i, ns, at, n, k, status) for i, (t, ns, at, n, k) in enumerate(m.packets)]
                rows = rows or [(key, None, None, None, None, None, None, None, status)]
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), schema)], schema=schema)

    return files.select(F.col(id_col).cast("long").alias("id"), F.col(media_col).alias("media")).mapInArrow(run, "id long, track long, codec string, packet long, timestamp_ns long, first_byte long, n_bytes long, keyframe boolean, status string")


def media_column(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and a media file (binary) that stores each text, padded, as 8-bit samples.

    One row per input row: null and empty texts are 64 zero bytes, equal texts equal files, a null id stays null; other
    columns are ignored whatever their names; an empty table gives an empty result. A file holds its whole text.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            files = [write_pcm(padded((t or "").encode("utf-8", "surrogatepass"))) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(files, pa.binary())], ["id", "media"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).mapInArrow(run, "id long, media binary")


def media_digest(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Store each whole text as a Matroska file, parse the file again and describe what came back.

    One row per input row: doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256,
    feature. Null and empty texts are 64 zero bytes. Equal texts have equal values; a null id keeps its row; other
    columns are ignored whatever their names. feature: tracks, clusters, cues, packets, milliseconds and a checksum
    of the packet table (timestamps and byte ranges).
    """

    def digest(text: str | None) -> tuple:
        raw = (text or "").encode("utf-8", "surrogatepass")
        stored = write_pcm(padded(raw))
        m = parse(stored)
        back = read_payload(stored, m)
        if any(stored[at : at + 4] != CLUSTER.to_bytes(4, "big") for _, _, at in m.cues):
            raise Broken("a cue that doesn't lead to a cluster")
        ranges = zlib.crc32(repr([p[:4] for p in m.packets]).encode())
        return len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(stored), hashlib.sha256(stored).hexdigest(), f"tracks={len(m.tracks)};clusters={m.clusters};cues={len(m.cues)};packets={len(m.packets)};ms={m.duration:.3f};table={ranges:08x}"

    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
    types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [digest(t) for t in batch.column(1).to_pylist()]
            if found:
                yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, t) for c, t in zip(zip(*found), types))], names)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


def op8_query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return media_digest(table(spark, sf_dir, "documents"))
