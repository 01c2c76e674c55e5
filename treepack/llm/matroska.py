"""Media columns in Matroska: a writer, and a reader that turns files into packet tables.

The reader walks EBML elements by their variable-length ids and sizes, takes
tracks, clusters, (simple) blocks with every kind of lacing, and cues, and
gives a row for each frame: track, timestamp, byte range. The writer stores
8-bit samples as an uncompressed audio track, several frames laced in a block.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treepack.llm.common import map_groups

FRAME = 576
RATE = 8000
FRAMES_PER_BLOCK = 8
BLOCKS_PER_CLUSTER = 32
# Element ids of the format.
EBML, SEGMENT, INFO, TRACKS, CLUSTER, CUES = 0x1A45DFA3, 0x18538067, 0x1549A966, 0x1654AE6B, 0x1F43B675, 0x1C53BB6B
DOC_TYPE, DOC_VERSION, DOC_READ_VERSION = 0x4282, 0x4287, 0x4285
TIMESTAMP_SCALE, DURATION, MUXER, WRITER = 0x2AD7B1, 0x4489, 0x4D80, 0x5741
TRACK_ENTRY, TRACK_NUMBER, TRACK_UID, TRACK_TYPE, FLAG_LACING, CODEC_ID = 0xAE, 0xD7, 0x73C5, 0x83, 0x9C, 0x86
AUDIO, SAMPLING, CHANNELS, BIT_DEPTH, DEFAULT_DURATION = 0xE1, 0xB5, 0x9F, 0x6264, 0x23E383
CLUSTER_TIME, SIMPLE_BLOCK, BLOCK_GROUP, BLOCK = 0xE7, 0xA3, 0xA0, 0xA1
CUE_POINT, CUE_TIME, CUE_POSITIONS, CUE_TRACK, CUE_CLUSTER = 0xBB, 0xB3, 0xB7, 0xF7, 0xF1
NO_LACING, XIPH, FIXED, EBML_LACING = 0, 1, 2, 3
_MASTERS = frozenset({SEGMENT, INFO, TRACKS, TRACK_ENTRY, AUDIO, CLUSTER, BLOCK_GROUP, CUES, CUE_POINT, CUE_POSITIONS})


class MediaError(ValueError):
    """The bytes are not a file of this format, or end too early."""


# --- writing ---------------------------------------------------------------


def vint(value: int, width: int = 0) -> bytes:
    """A size with its length marker, in as few bytes as hold it (all ones is kept for unknown sizes)."""
    width = width or next(w for w in range(1, 9) if value < (1 << 7 * w) - 1)
    return (value | 1 << 7 * width).to_bytes(width, "big")


def element(ident: int, body: bytes) -> bytes:
    return ident.to_bytes((ident.bit_length() + 7) // 8, "big") + vint(len(body)) + body


def uint(ident: int, value: int) -> bytes:
    return element(ident, value.to_bytes(max(1, (value.bit_length() + 7) // 8), "big"))


def lace(frames: list[bytes], kind: int) -> bytes:
    """Frames of one block with the sizes that the kind of lacing writes down."""
    sizes = [len(f) for f in frames]
    if kind == NO_LACING:
        return frames[0]
    head = bytes([len(frames) - 1])
    if kind == XIPH:
        head += b"".join(b"\xff" * (s // 255) + bytes([s % 255]) for s in sizes[:-1])
    elif kind == EBML_LACING:
        head += vint(sizes[0])
        for a, b in zip(sizes, sizes[1:-1]):
            width = next(w for w in range(1, 9) if abs(b - a) < (1 << 7 * w - 1) - 1)
            head += vint(b - a + (1 << 7 * width - 1) - 1, width)
    return head + b"".join(frames)


def write(payload: bytes, *, frame: int = FRAME, rate: int = RATE, per_block: int = FRAMES_PER_BLOCK, lacing: int = FIXED) -> bytes:
    """payload as one track of frames; cues point to each cluster."""
    frames = [payload[i : i + frame] for i in range(0, len(payload), frame)]
    millis = lambda k: k * frame * 1000 // rate
    info = uint(TIMESTAMP_SCALE, 1_000_000) + element(DURATION, struct.pack(">d", len(payload) * 1000 / rate)) + element(MUXER, b"columns") + element(WRITER, b"columns")
    audio = element(SAMPLING, struct.pack(">d", float(rate))) + uint(CHANNELS, 1) + uint(BIT_DEPTH, 8)
    entry = uint(TRACK_NUMBER, 1) + uint(TRACK_UID, 1) + uint(TRACK_TYPE, 2) + uint(FLAG_LACING, 1) + uint(DEFAULT_DURATION, frame * 10**9 // rate) + element(CODEC_ID, b"A_PCM/INT/LIT") + element(AUDIO, audio)
    body = [element(INFO, info), element(TRACKS, element(TRACK_ENTRY, entry))]
    at, cues, step = sum(map(len, body)), [], per_block * BLOCKS_PER_CLUSTER
    for first in range(0, len(frames), step):
        parts = [uint(CLUSTER_TIME, millis(first))]
        for k in range(first, min(first + step, len(frames)), per_block):
            group = frames[k : min(k + per_block, first + step)]
            kind = lacing if len(group) > 1 else NO_LACING
            if kind == FIXED and len({len(g) for g in group}) > 1:
                kind = EBML_LACING
            parts.append(element(SIMPLE_BLOCK, vint(1) + struct.pack(">hB", millis(k) - millis(first), 0x80 | kind << 1) + lace(group, kind)))
        body.append(element(CLUSTER, b"".join(parts)))
        cues.append(element(CUE_POINT, uint(CUE_TIME, millis(first)) + element(CUE_POSITIONS, uint(CUE_TRACK, 1) + uint(CUE_CLUSTER, at))))
        at += len(body[-1])
    body.append(element(CUES, b"".join(cues)))
    head = uint(0x4286, 1) + uint(0x42F7, 1) + uint(0x42F2, 4) + uint(0x42F3, 8) + element(DOC_TYPE, b"matroska") + uint(DOC_VERSION, 4) + uint(DOC_READ_VERSION, 2)
    return element(EBML, head) + element(SEGMENT, b"".join(body))


# --- reading ---------------------------------------------------------------


def read_vint(data: bytes, at: int, end: int, keep_marker: bool = False) -> tuple[int | None, int]:
    """(value, next position); None for an unknown size."""
    if at >= end or data[at] == 0:
        raise MediaError(f"no variable-length number at byte {at}")
    width = 9 - data[at].bit_length()
    if at + width > end:
        raise MediaError(f"a number of {width} bytes at byte {at} runs past the end")
    raw = int.from_bytes(data[at : at + width], "big")
    if keep_marker:
        return raw, at + width
    value = raw & (1 << 7 * width) - 1
    return None if value == (1 << 7 * width) - 1 else value, at + width


def elements(data: bytes, at: int, end: int):
    """(id, body start, body end) of the elements in a range; an unknown size runs to the next sibling cluster or the end."""
    while at < end:
        ident, at = read_vint(data, at, end, keep_marker=True)
        size, at = read_vint(data, at, end)
        if size is None:
            if ident not in (SEGMENT, CLUSTER):
                raise MediaError(f"unknown size of element {ident:#x}")
            stop = end if ident == SEGMENT else _cluster_end(data, at, end)
        else:
            stop = at + size
        if stop > end:
            raise MediaError(f"element {ident:#x} at byte {at} runs past the end")
        yield ident, at, stop
        at = stop


def _cluster_end(data: bytes, at: int, end: int) -> int:
    while at < end:
        ident, body = read_vint(data, at, end, keep_marker=True)
        if ident in (CLUSTER, CUES, TRACKS, INFO):
            return at
        size, body = read_vint(data, body, end)
        at = body + (size or 0)
    return end


@dataclass
class Media:
    scale: int = 1_000_000
    duration: float = 0.0
    tracks: dict[int, dict] = field(default_factory=dict)
    packets: list[tuple[int, int, int, int, int, int]] = field(default_factory=list)  # track, timestamp ns, start, length, block, frame in block
    clusters: list[tuple[int, int]] = field(default_factory=list)  # position from the segment's start, time
    cues: list[tuple[int, int, int]] = field(default_factory=list)  # time, track, cluster position


def read(data: bytes) -> Media:
    out, seen = Media(), False
    for ident, a, b in elements(data, 0, len(data)):
        if ident == EBML:
            kind = next((data[x:y] for i, x, y in elements(data, a, b) if i == DOC_TYPE), b"matroska")
            if kind not in (b"matroska", b"webm"):
                raise MediaError(f"document type {kind!r}")
            seen = True
        elif ident == SEGMENT and seen:
            _segment(data, a, b, out)
    if not seen:
        raise MediaError("no header")
    return out


def _number(data: bytes, a: int, b: int) -> int:
    return int.from_bytes(data[a:b], "big")


def _real(data: bytes, a: int, b: int) -> float:
    return struct.unpack(">f" if b - a == 4 else ">d", data[a:b])[0] if b > a else 0.0


def _segment(data: bytes, start: int, end: int, out: Media) -> None:
    block = 0
    for ident, a, b in elements(data, start, end):
        if ident == INFO:
            for i, x, y in elements(data, a, b):
                if i == TIMESTAMP_SCALE:
                    out.scale = _number(data, x, y)
                elif i == DURATION:
                    out.duration = _real(data, x, y)
        elif ident == TRACKS:
            for i, x, y in elements(data, a, b):
                if i == TRACK_ENTRY:
                    _track(data, x, y, out)
        elif ident == CLUSTER:
            time = 0
            for i, x, y in elements(data, a, b):
                if i == CLUSTER_TIME:
                    time = _number(data, x, y)
                    out.clusters.append((a - start, time))
                elif i == SIMPLE_BLOCK:
                    _block(data, x, y, time, block, out)
                    block += 1
                elif i == BLOCK_GROUP:
                    for j, p, q in elements(data, x, y):
                        if j == BLOCK:
                            _block(data, p, q, time, block, out)
                            block += 1
        elif ident == CUES:
            for i, x, y in elements(data, a, b):
                if i == CUE_POINT:
                    time, track, where = 0, 0, 0
                    for j, p, q in elements(data, x, y):
                        if j == CUE_TIME:
                            time = _number(data, p, q)
                        elif j == CUE_POSITIONS:
                            for k, r, s in elements(data, p, q):
                                track, where = (_number(data, r, s), where) if k == CUE_TRACK else (track, _number(data, r, s)) if k == CUE_CLUSTER else (track, where)
                    out.cues.append((time, track, where))


def _track(data: bytes, a: int, b: int, out: Media) -> None:
    t = {"number": 0, "type": 0, "codec": "", "frame_ns": 0, "rate": 0.0, "bits": 0}
    for i, x, y in elements(data, a, b):
        if i == TRACK_NUMBER:
            t["number"] = _number(data, x, y)
        elif i == TRACK_TYPE:
            t["type"] = _number(data, x, y)
        elif i == CODEC_ID:
            t["codec"] = data[x:y].decode("latin-1")
        elif i == DEFAULT_DURATION:
            t["frame_ns"] = _number(data, x, y)
        elif i == AUDIO:
            for j, p, q in elements(data, x, y):
                if j == SAMPLING:
                    t["rate"] = _real(data, p, q)
                elif j == BIT_DEPTH:
                    t["bits"] = _number(data, p, q)
    out.tracks[t["number"]] = t


def _block(data: bytes, a: int, b: int, cluster_time: int, block: int, out: Media) -> None:
    track, at = read_vint(data, a, b)
    if at + 3 > b:
        raise MediaError("a block without its header")
    offset, flags = struct.unpack_from(">hB", data, at)
    at += 3
    kind = flags >> 1 & 3
    if kind == NO_LACING:
        sizes = [b - at]
    else:
        if at >= b:
            raise MediaError("a laced block without its count")
        n, at = data[at] + 1, at + 1
        sizes = []
        if kind == FIXED:
            if (b - at) % n:
                raise MediaError("frames of a block differ in size")
            sizes = [(b - at) // n] * n
        else:
            for k in range(n - 1):
                if kind == XIPH:
                    size = 0
                    while at < b:
                        size, at = size + data[at], at + 1
                        if data[at - 1] != 255:
                            break
                elif k == 0:
                    size, at = read_vint(data, at, b)
                else:
                    width = 9 - data[at].bit_length()
                    raw, at = read_vint(data, at, b, keep_marker=True)
                    size = sizes[-1] + (raw & (1 << 7 * width) - 1) - ((1 << 7 * width - 1) - 1)
                sizes.append(size)
            sizes.append(b - at - sum(sizes))
        if min(sizes) < 0:
            raise MediaError("frames run past their block")
    time, step = (cluster_time + offset) * out.scale, out.tracks.get(track, {}).get("frame_ns", 0)
    for k, size in enumerate(sizes):
        out.packets.append((track, time + k * step, at, size, block, k))
        at += size


# --- columns ---------------------------------------------------------------


def padded(text: bytes | None, unit: int = FRAME) -> bytes:
    """The bytes of a text with 255s up to a positive multiple of a frame."""
    text = text or b""
    return text + b"\xff" * (unit - len(text) % unit if len(text) % unit or not text else 0)


def to_media(docs: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, media binary) for each row; null counts as empty."""
    return map_groups(docs.select(F.col("doc_id").cast("long"), "text"), lambda rows: [(d, len(t or b""), write(padded(t))) for d, t in rows], "doc_id long, n_bytes long, media binary")


def packet_table(media: DataFrame) -> DataFrame:
    """(doc_id, track, timestamp_ns, start, length, block, frame) of every frame; a null column gives no rows, a broken file raises."""

    def many(rows):
        return [(d, *p) for d, m in rows if m is not None for p in read(m).packets]

    return map_groups(media.select("doc_id", "media"), many, "doc_id long, track int, timestamp_ns long, start long, length long, block int, frame int", nbytes=1 << 20)


def cue_table(media: DataFrame) -> DataFrame:
    """(doc_id, time, track, cluster) of every cue."""
    return map_groups(media.select("doc_id", "media"), lambda rows: [(d, *c) for d, m in rows if m is not None for c in read(m).cues], "doc_id long, time long, track int, cluster long")


def _features(m: Media, payload: bytes) -> str:
    a = np.frombuffer(payload, np.uint8)
    signed = a.astype(np.float32) - 128
    p = np.bincount(a, minlength=256) / max(1, len(a))
    p = p[p > 0]
    crossings = int(np.count_nonzero((a[1:] >= 128) != (a[:-1] >= 128)))
    last = m.packets[-1][1] if m.packets else 0
    blocks = m.packets[-1][4] + 1 if m.packets else 0
    entropy = float(-(p * np.log2(p)).sum()) + 0.0
    return f"frames={len(m.packets)};blocks={blocks};clusters={len(m.clusters)};cues={len(m.cues)};last_ns={last};mean={a.mean():.4f};rms={float(np.sqrt((signed.astype(np.float64) ** 2).mean())):.4f};crossings={crossings};entropy={entropy:.4f}"


def from_media(media: DataFrame) -> DataFrame:
    """Reads the stored bytes back, frame by frame, and digests them."""
    sha = lambda b: hashlib.sha256(b).hexdigest()

    def many(rows):
        out = []
        for doc_id, n, stored in rows:
            m = read(stored)
            payload = b"".join([stored[s : s + k] for _, _, s, k, _, _ in m.packets])
            out.append((doc_id, n, len(payload), sha(payload), zlib.crc32(payload[-32:]), len(stored), sha(stored), _features(m, payload)))
        return out

    return map_groups(media, many, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string", nbytes=1 << 21)
