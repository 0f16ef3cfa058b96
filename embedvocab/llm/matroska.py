"""Matroska media columns: a writer, and a parser that turns stored bytes into packet tables.

The writer stores a payload of 8-bit samples as one PCM track: EBML header, segment information, a track entry,
clusters of laced simple blocks and a cue for each cluster. The parser knows nothing of the writer: it follows
variable-length element ids and sizes, unknown sizes included, and all four kinds of lacing, and gives one row a
frame with its timestamp, track and byte range. Each text is muxed and parsed by itself, in one task.

Null and empty texts give one frame of padding. Equal texts give equal bytes. Rows with null ids and repeated rows
are stored like others. A very long text is muxed and parsed whole, in a small multiple of its length. Extra columns, whatever
their names, are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from embedvocab.llm.common import arrow_rows, per_document

#: Fixed values of the format: element ids.
EBML, VERSION, READ_VERSION, MAX_ID, MAX_SIZE, DOC_TYPE, DOC_VERSION, DOC_READ = 0x1A45DFA3, 0x4286, 0x42F7, 0x42F2, 0x42F3, 0x4282, 0x4287, 0x4285
SEGMENT, INFO, SCALE, DURATION, MUXER, WRITER = 0x18538067, 0x1549A966, 0x2AD7B1, 0x4489, 0x4D80, 0x5741
TRACKS, ENTRY, NUMBER, UID, TYPE, CODEC, AUDIO, RATE, CHANNELS, DEPTH = 0x1654AE6B, 0xAE, 0xD7, 0x73C5, 0x83, 0x86, 0xE1, 0xB5, 0x9F, 0x6264
CLUSTER, TIMESTAMP, SIMPLE, GROUP, BLOCK = 0x1F43B675, 0xE7, 0xA3, 0xA0, 0xA1
CUES, POINT, CUE_TIME, POSITIONS, CUE_TRACK, CUE_CLUSTER = 0x1C53BB6B, 0xBB, 0xB3, 0xB7, 0xF7, 0xF1
MASTERS = {SEGMENT, INFO, TRACKS, ENTRY, AUDIO, CLUSTER, GROUP, CUES, POINT, POSITIONS}
TOP = {INFO, TRACKS, CLUSTER, CUES}
LACING = {"none": 0, "xiph": 1, "fixed": 2, "ebml": 3}

FRAME, SAMPLE_RATE = 576, 8000
FRAME_MS = FRAME * 1000 // SAMPLE_RATE


# ---------------------------------------------------------------- writing

def vint(n: int, least: int = 1) -> bytes:
    """A number with its length marker; all ones is kept for unknown sizes."""
    width = least
    while n >= (1 << 7 * width) - 1:
        width += 1
    return (n | 1 << 7 * width).to_bytes(width, "big")


def element(key: int, body: bytes) -> bytes:
    return key.to_bytes((key.bit_length() + 7) // 8, "big") + vint(len(body)) + body


def number(key: int, n: int) -> bytes:
    return element(key, n.to_bytes(max(1, (n.bit_length() + 7) // 8), "big"))


def laced(frames: list[bytes], lacing: str) -> bytes:
    """The lace header and the frames of a block."""
    sizes = [len(f) for f in frames]
    if lacing == "none":
        head = b""
    elif lacing == "fixed":
        head = bytes([len(frames) - 1])
    elif lacing == "xiph":
        head = bytes([len(frames) - 1]) + b"".join(b"\xff" * (s // 255) + bytes([s % 255]) for s in sizes[:-1])
    else:
        head = bytes([len(frames) - 1]) + vint(sizes[0])
        for a, b in zip(sizes, sizes[1:-1]):
            width = 1
            while abs(b - a) >= (1 << 7 * width - 1) - 1:
                width += 1
            head += vint(b - a + (1 << 7 * width - 1) - 1, width)
    return head + b"".join(frames)


def mux(payload: bytes, lacing: str = "fixed", lace: int = 8, blocks: int = 32) -> bytes:
    """A file with the payload, a multiple of the frame size, as one PCM track."""
    head = element(EBML, number(VERSION, 1) + number(READ_VERSION, 1) + number(MAX_ID, 4) + number(MAX_SIZE, 8) + element(DOC_TYPE, b"matroska") + number(DOC_VERSION, 4) + number(DOC_READ, 2))
    lace = 1 if lacing == "none" else lace
    audio = element(RATE, struct.pack(">d", SAMPLE_RATE)) + number(CHANNELS, 1) + number(DEPTH, 8)
    info = element(INFO, number(SCALE, 1_000_000) + element(MUXER, b"embedvocab") + element(WRITER, b"embedvocab") + element(DURATION, struct.pack(">d", len(payload) // FRAME * FRAME_MS)))
    tracks = element(TRACKS, element(ENTRY, number(NUMBER, 1) + number(UID, 1) + number(TYPE, 2) + element(CODEC, b"A_PCM/INT/LIT") + element(AUDIO, audio)))
    body, at, cues = [info, tracks], len(info) + len(tracks), []
    step = FRAME * lace
    for c in range(0, len(payload), step * blocks):
        start = c // FRAME * FRAME_MS
        parts = [number(TIMESTAMP, start)]
        for b in range(c, min(c + step * blocks, len(payload)), step):
            frames = [payload[f:f + FRAME] for f in range(b, min(b + step, len(payload)), FRAME)]
            kind = lacing if len(frames) > 1 else "none"
            parts.append(element(SIMPLE, vint(1) + struct.pack(">hB", b // FRAME * FRAME_MS - start, 0x80 | LACING[kind] << 1) + laced(frames, kind)))
        cluster = element(CLUSTER, b"".join(parts))
        cues.append(element(POINT, number(CUE_TIME, start) + element(POSITIONS, number(CUE_TRACK, 1) + number(CUE_CLUSTER, at))))
        body.append(cluster)
        at += len(cluster)
    body.append(element(CUES, b"".join(cues)))
    return head + element(SEGMENT, b"".join(body))


# ---------------------------------------------------------------- parsing

def read_vint(data: bytes, at: int, marker: bool) -> tuple[int | None, int]:
    """The number at a position, with its marker for ids, and where it ends; None for an unknown size."""
    first = data[at]
    if not first:
        raise ValueError(f"no element at byte {at}")
    width = 9 - first.bit_length()
    n = int.from_bytes(data[at:at + width], "big")
    if len(data) < at + width:
        raise ValueError(f"the file ends in a number at byte {at}")
    if marker:
        return n, at + width
    n &= (1 << 7 * width) - 1
    return (None if n == (1 << 7 * width) - 1 else n), at + width


def elements(data: bytes, at: int, end: int, parent: int | None = None) -> Iterator[tuple[int, int, int, int]]:
    """(id, where it begins, where its body begins and ends) of the children of an element."""
    while at < end:
        begin = at
        key, at = read_vint(data, at, True)
        if parent == CLUSTER and (key in TOP or key == SEGMENT):
            return  # a cluster of unknown size ends where its parent's next child begins
        size, at = read_vint(data, at, False)
        stop = end if size is None else at + size
        if stop > end:
            raise ValueError(f"the element at byte {begin} ends beyond its parent")
        if size is None and key == CLUSTER:
            last = at
            for *_, last in elements(data, at, end, CLUSTER):
                pass
            stop = last
        yield key, begin, at, stop
        at = stop


def frame_ranges(data: bytes, at: int, end: int, kind: int) -> list[tuple[int, int]]:
    """(offset, size) of the frames of a block after its head."""
    if not kind:
        return [(at, end - at)]
    n, at = data[at] + 1, at + 1
    sizes: list[int] = []
    if kind == LACING["xiph"]:
        for _ in range(n - 1):
            s = 0
            while data[at] == 255:
                s, at = s + 255, at + 1
            sizes.append(s + data[at])
            at += 1
    elif kind == LACING["ebml"]:
        for i in range(n - 1):
            x, after = read_vint(data, at, False)
            sizes.append(x if not i else sizes[-1] + x - ((1 << 7 * (after - at) - 1) - 1))
            at = after
    else:
        sizes = [(end - at) // n] * (n - 1)
    sizes.append(end - at - sum(sizes))
    if min(sizes) < 0:
        raise ValueError(f"the lace at byte {at} is longer than its block")
    return [(at + sum(sizes[:i]), s) for i, s in enumerate(sizes)] if kind != LACING["fixed"] else [(at + i * sizes[0], s) for i, s in enumerate(sizes)]


def parse(data: bytes) -> tuple[list[tuple[int, int, int, int, int, bool]], list[tuple[int, int, int]], dict[int, dict]]:
    """Packets (track, timestamp in ns, cluster offset, byte offset, size, keyframe), cues (time, track, offset), tracks."""
    packets, cues, tracks, scale = [], [], {}, 1_000_000
    whole = lambda s, e: int.from_bytes(data[s:e], "big")
    for key, _, s, e in elements(data, 0, len(data)):
        if key != SEGMENT:
            continue
        for part, begin, ps, pe in elements(data, s, e):
            if part == INFO:
                scale = next((whole(a, b) for k, _, a, b in elements(data, ps, pe) if k == SCALE), scale)
            elif part == TRACKS:
                for _, _, es, ee in elements(data, ps, pe):
                    own = {k: (a, b) for k, _, a, b in elements(data, es, ee)}
                    sound = {k: (a, b) for k, _, a, b in elements(data, *own[AUDIO])} if AUDIO in own else {}
                    rate = struct.unpack(">d", data[slice(*sound[RATE])])[0] if RATE in sound else None
                    tracks[whole(*own[NUMBER])] = {"codec": data[slice(*own[CODEC])].decode(), "rate": rate, "depth": whole(*sound[DEPTH]) if DEPTH in sound else None}
            elif part == CUES:
                for _, _, cs, ce in elements(data, ps, pe):
                    point = {k: (a, b) for k, _, a, b in elements(data, cs, ce)}
                    where = {k: (a, b) for k, _, a, b in elements(data, *point[POSITIONS])}
                    cues.append((whole(*point[CUE_TIME]) * scale, whole(*where[CUE_TRACK]), s + whole(*where[CUE_CLUSTER])))
            elif part == CLUSTER:
                base = 0
                for k, _, bs, be in elements(data, ps, pe, CLUSTER):
                    if k == TIMESTAMP:
                        base = whole(bs, be)
                    for bk, _, a, b in (elements(data, bs, be) if k == GROUP else [(k, 0, bs, be)]):
                        if bk not in (SIMPLE, BLOCK):
                            continue
                        track, at = read_vint(data, a, False)
                        rel, flags = struct.unpack(">hB", data[at:at + 3])
                        rate = (tracks.get(track) or {}).get("rate")
                        stamp = (base + rel) * scale
                        for offset, size in frame_ranges(data, at + 3, b, flags >> 1 & 3):
                            packets.append((track, stamp, begin, offset, size, bool(flags & 0x80)))
                            # laced frames follow each other: PCM tells how long a frame lasts
                            stamp += round(size * 1_000_000_000 / rate) if rate else 0
    return packets, cues, tracks


# ---------------------------------------------------------------- columns

def payload_of(text: bytes) -> bytes:
    return text + b"\xff" * (max(FRAME, -(-len(text) // FRAME) * FRAME) - len(text))


def store(docs: DataFrame, lacing: str = "fixed") -> DataFrame:
    """(doc_id, media): the texts as Matroska files."""
    schema = pa.schema([("doc_id", pa.int64()), ("media", pa.binary())])
    return per_document(docs, lambda ids, texts: ((i, mux(payload_of(t), lacing)) for i, t in zip(ids, texts, strict=True)), schema, "doc_id long, media binary")


_PACKETS = pa.schema([("doc_id", pa.int64()), ("track", pa.int32()), ("timestamp_ns", pa.int64()), ("cluster_offset", pa.int64()), ("offset", pa.int64()), ("size", pa.int64()), ("keyframe", pa.bool_())])


def packets(media: DataFrame) -> DataFrame:
    """(doc_id, track, timestamp_ns, cluster_offset, offset, size, keyframe) of (doc_id, media): a row a frame; null media has none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for doc_id, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if data.is_valid:
                    yield from arrow_rows(_PACKETS, ((doc_id, *p) for p in parse(data.as_py())[0])).to_batches()

    return media.select("doc_id", "media").mapInArrow(run, "doc_id long, track int, timestamp_ns long, cluster_offset long, offset long, size long, keyframe boolean")


def cue_points(media: DataFrame) -> DataFrame:
    """(doc_id, timestamp_ns, track, cluster_offset) of (doc_id, media): where a reader may seek to."""
    schema = pa.schema([("doc_id", pa.int64()), ("timestamp_ns", pa.int64()), ("track", pa.int32()), ("cluster_offset", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for doc_id, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if data.is_valid:
                    yield from arrow_rows(schema, ((doc_id, *c) for c in parse(data.as_py())[1])).to_batches()

    return media.select("doc_id", "media").mapInArrow(run, "doc_id long, timestamp_ns long, track int, cluster_offset long")


def features(samples: bytes, found: list[tuple], cues: list[tuple]) -> str:
    """Packets, seek points, duration, and level, spread and crossings of the middle of the unsigned samples."""
    x = np.frombuffer(samples, np.uint8)
    hist = np.bincount(x, minlength=256)
    n, values = len(x), np.arange(256)
    mean = float(hist @ values) / n
    rms = float(np.sqrt(hist @ (values - 128.0) ** 2 / n))
    crossings = int(np.count_nonzero(np.diff((x >= 128).view(np.int8))))
    p = hist[hist > 0] / n
    return f"packets={len(found)};cues={len(cues)};ms={(found[-1][1] // 1_000_000 + FRAME_MS) if found else 0};mean={mean:.4f};rms={rms:.4f};crossings={crossings};entropy={float(-(p * np.log2(p)).sum()):.4f}"


def digest(docs: DataFrame) -> DataFrame:
    """What is read back of each stored text: payload and media sizes, checksums and features."""
    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string())])

    def score(ids: list, texts: list[bytes]) -> Iterator[tuple]:
        for doc_id, text in zip(ids, texts, strict=True):
            media = mux(payload_of(text))
            found, cues, _ = parse(media)
            back = b"".join(media[o:o + s] for _, _, _, o, s, _ in sorted(found, key=lambda p: (p[0], p[1], p[3])))
            yield doc_id, len(text), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-32:]), len(media), hashlib.sha256(media).hexdigest(), features(back, found, cues)

    return per_document(docs, score, schema, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")
