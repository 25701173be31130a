"""Matroska media columns.

``parse`` walks the variable-length EBML elements of a file (known and unknown sizes), its tracks,
clusters, simple blocks and block groups, undoes Xiph, fixed-size and EBML lacing, reads the cues and
gives a packet table: track, timestamp, byte range and key-frame flag of every packet. ``mux`` writes
the same structures, so that bytes stored as 8-bit PCM packets come back without loss.

Cases: null and empty payloads are padded to one unit of spaces; payloads of any length are stored whole;
equal payloads give equal files; bytes that are no Matroska file raise ``ValueError`` in ``parse``
and give no packets in ``packet_table``; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import hashlib
import struct
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from zlib import crc32

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Element ids of the container format.
EBML, SEGMENT, SEEK_HEAD, INFO, TRACKS, CLUSTER, CUES, VOID = 0x1A45DFA3, 0x18538067, 0x114D9B74, 0x1549A966, 0x1654AE6B, 0x1F43B675, 0x1C53BB6B, 0xEC
EBML_VERSION, EBML_READ_VERSION, EBML_MAX_ID, EBML_MAX_SIZE, DOC_TYPE, DOC_TYPE_VERSION, DOC_TYPE_READ = 0x4286, 0x42F7, 0x42F2, 0x42F3, 0x4282, 0x4287, 0x4285
TIMESTAMP_SCALE, DURATION, MUXING_APP, WRITING_APP = 0x2AD7B1, 0x4489, 0x4D80, 0x5741
TRACK_ENTRY, TRACK_NUMBER, TRACK_UID, TRACK_TYPE, CODEC_ID, FLAG_LACING, DEFAULT_DURATION = 0xAE, 0xD7, 0x73C5, 0x83, 0x86, 0x9C, 0x23E383
AUDIO, SAMPLING_FREQUENCY, CHANNELS, BIT_DEPTH = 0xE1, 0xB5, 0x9F, 0x6264
TIMESTAMP, SIMPLE_BLOCK, BLOCK_GROUP, BLOCK, BLOCK_DURATION, REFERENCE_BLOCK = 0xE7, 0xA3, 0xA0, 0xA1, 0x9B, 0xFB
CUE_POINT, CUE_TIME, CUE_TRACK_POSITIONS, CUE_TRACK, CUE_CLUSTER_POSITION = 0xBB, 0xB3, 0xB7, 0xF7, 0xF1
SEGMENT_CHILDREN = {SEEK_HEAD, INFO, TRACKS, CLUSTER, CUES, 0x1941A469, 0x1043A770, 0x1254C367}

UNIT = 192  #: bytes of one packet
PACKETS_A_BLOCK, BLOCKS_A_CLUSTER = 16, 64
RATE = 8000


@dataclass
class Packet:
    track: int
    timestamp: int  # in units of the timestamp scale
    offset: int
    size: int
    keyframe: bool


@dataclass
class Movie:
    doc_type: str = ""
    scale: int = 1_000_000
    tracks: dict[int, dict] = field(default_factory=dict)
    packets: list[Packet] = field(default_factory=list)
    clusters: list[int] = field(default_factory=list)
    cues: list[tuple[int, int, int]] = field(default_factory=list)  # time, track, cluster position
    segment_at: int = 0
    laced: list[int] = field(default_factory=lambda: [0, 0, 0, 0])  # blocks without, with Xiph, fixed and EBML lacing


# --- reading -----------------------------------------------------------------------------------------


def element_id(data: bytes, at: int) -> tuple[int, int]:
    first = data[at]
    width = 9 - first.bit_length()
    if not first or width > 4:
        raise ValueError(f"no element id at byte {at}")
    return int.from_bytes(data[at : at + width], "big"), at + width


def element_size(data: bytes, at: int) -> tuple[int | None, int]:
    """None: unknown size."""
    first = data[at]
    if not first:
        raise ValueError(f"no element size at byte {at}")
    width = 9 - first.bit_length()
    value = int.from_bytes(data[at : at + width], "big") & ((1 << 7 * width) - 1)
    return (None if value == (1 << 7 * width) - 1 else value), at + width


def children(data: bytes, at: int, end: int, closes: set[int] = frozenset()) -> Iterator[tuple[int, int, int]]:
    """Id, payload start and end of each element; one of unknown size ends at an id of its parent's level."""
    while at < end:
        kind, body = element_id(data, at)
        size, body = element_size(data, body)
        if size is None:
            stop = end if kind == SEGMENT else _open_end(data, body, end, SEGMENT_CHILDREN | closes)
        else:
            stop = body + size
        if stop > end:
            raise ValueError(f"element {kind:#x} at byte {at} passes the end of its parent")
        yield kind, body, stop
        at = stop


def _open_end(data: bytes, at: int, end: int, closes: set[int]) -> int:
    while at < end:
        kind, body = element_id(data, at)
        if kind in closes:
            return at
        size, body = element_size(data, body)
        if size is None:
            raise ValueError("unknown sizes cannot nest here")
        at = body + size
    return end


def uint(data: bytes, a: int, b: int) -> int:
    return int.from_bytes(data[a:b], "big")


def real(data: bytes, a: int, b: int) -> float:
    return struct.unpack({4: ">f", 8: ">d"}[b - a], data[a:b])[0] if b > a else 0.0


def lace_sizes(data: bytes, at: int, end: int, mode: int) -> tuple[list[int], int]:
    """Sizes of the frames of a laced block, and where the first begins."""
    n = data[at] + 1
    at += 1
    if mode == 2:
        if (end - at) % n:
            raise ValueError("fixed lacing does not divide the block")
        return [(end - at) // n] * n, at
    sizes: list[int] = []
    if mode == 1:
        for _ in range(n - 1):
            size = 0
            while data[at] == 255:
                size, at = size + 255, at + 1
            sizes.append(size + data[at])
            at += 1
    elif n > 1:
        size, at = element_size(data, at)
        sizes.append(size)
        for _ in range(n - 2):
            width = 9 - data[at].bit_length()
            raw, at = element_size(data, at)
            raw = (1 << 7 * width) - 1 if raw is None else raw
            sizes.append(sizes[-1] + raw - ((1 << 7 * width - 1) - 1))
    sizes.append(end - at - sum(sizes))
    if min(sizes) < 0:
        raise ValueError("lace sizes pass the end of the block")
    return sizes, at


def _block(movie: Movie, data: bytes, a: int, b: int, cluster_time: int, simple: bool, keyframe: bool) -> None:
    track, at = element_size(data, a)
    (shift,) = struct.unpack(">h", data[at : at + 2])
    flags = data[at + 2]
    mode, at = flags >> 1 & 3, at + 3
    movie.laced[mode] += 1
    sizes, at = lace_sizes(data, at, b, mode) if mode else ([b - at], at)
    step = movie.tracks.get(track, {}).get("default_duration", 0) / movie.scale
    key = bool(flags & 128) if simple else keyframe
    for i, size in enumerate(sizes):
        movie.packets.append(Packet(track, cluster_time + shift + round(i * step), at, size, key))
        at += size


def parse(data: bytes) -> Movie:
    movie = Movie()
    top = children(data, 0, len(data))
    try:
        for kind, a, b in top:
            if kind == EBML:
                movie.doc_type = next((data[x:y].decode("ascii") for k, x, y in children(data, a, b) if k == DOC_TYPE), "matroska")
            elif kind == SEGMENT:
                _segment(movie, data, a, b)
    except (IndexError, struct.error, KeyError) as broken:
        raise ValueError(f"the file is cut off or broken: {broken}") from broken
    if not movie.doc_type:
        raise ValueError("no EBML header")
    return movie


def _segment(movie: Movie, data: bytes, start: int, end: int) -> None:
    movie.segment_at = start
    for kind, a, b in children(data, start, end):
        if kind == INFO:
            for k, x, y in children(data, a, b):
                if k == TIMESTAMP_SCALE:
                    movie.scale = uint(data, x, y)
        elif kind == TRACKS:
            for k, x, y in children(data, a, b):
                if k == TRACK_ENTRY:
                    _track(movie, data, x, y)
        elif kind == CLUSTER:
            movie.clusters.append(a)
            time = 0
            for k, x, y in children(data, a, b):
                if k == TIMESTAMP:
                    time = uint(data, x, y)
                elif k == SIMPLE_BLOCK:
                    _block(movie, data, x, y, time, True, False)
                elif k == BLOCK_GROUP:
                    inside = list(children(data, x, y))
                    key = all(i != REFERENCE_BLOCK for i, _, _ in inside)
                    for i, p, q in inside:
                        if i == BLOCK:
                            _block(movie, data, p, q, time, False, key)
        elif kind == CUES:
            for k, x, y in children(data, a, b):
                if k == CUE_POINT:
                    inside = list(children(data, x, y))
                    time = next((uint(data, p, q) for i, p, q in inside if i == CUE_TIME), 0)
                    for i, p, q in inside:
                        if i == CUE_TRACK_POSITIONS:
                            of = {j: uint(data, m, n) for j, m, n in children(data, p, q)}
                            movie.cues.append((time, of.get(CUE_TRACK, 0), of.get(CUE_CLUSTER_POSITION, 0)))


def _track(movie: Movie, data: bytes, a: int, b: int) -> None:
    of: dict = {}
    for k, x, y in children(data, a, b):
        if k in (TRACK_NUMBER, TRACK_TYPE):
            of["number" if k == TRACK_NUMBER else "type"] = uint(data, x, y)
        elif k == DEFAULT_DURATION:
            of["default_duration"] = uint(data, x, y)
        elif k == CODEC_ID:
            of["codec"] = data[x:y].rstrip(b"\0").decode("ascii")
        elif k == AUDIO:
            for i, p, q in children(data, x, y):
                if i == SAMPLING_FREQUENCY:
                    of["rate"] = real(data, p, q)
                elif i in (CHANNELS, BIT_DEPTH):
                    of["channels" if i == CHANNELS else "bits"] = uint(data, p, q)
    movie.tracks[of.get("number", 0)] = of


# --- writing ------------------------------------------------------------------------------------------


def size_bytes(n: int, width: int = 0) -> bytes:
    while not width or n >= (1 << 7 * width) - 1:
        width += 1
    return (n | 1 << 7 * width).to_bytes(width, "big")


def element(kind: int, payload: bytes, width: int = 0) -> bytes:
    return kind.to_bytes((kind.bit_length() + 7) // 8, "big") + size_bytes(len(payload), width) + payload


def number(kind: int, n: int) -> bytes:
    return element(kind, n.to_bytes(max(1, (n.bit_length() + 7) // 8), "big"))


def lace(frames: list[bytes], mode: int) -> bytes:
    """The lace header and the frames. mode: 1 Xiph, 2 fixed, 3 EBML."""
    head = bytes([len(frames) - 1])
    if mode == 1:
        head += b"".join(b"\xff" * (len(f) // 255) + bytes([len(f) % 255]) for f in frames[:-1])
    elif mode == 3 and len(frames) > 1:
        head += size_bytes(len(frames[0]))
        for before, f in zip(frames[:-2], frames[1:-1], strict=True):
            d, width = len(f) - len(before), 1
            while not -((1 << 7 * width - 1) - 1) <= d <= (1 << 7 * width - 1) - 1:
                width += 1
            head += (d + (1 << 7 * width - 1) - 1 | 1 << 7 * width).to_bytes(width, "big")
    return head + b"".join(frames)


def _head() -> bytes:
    track = b"".join([number(TRACK_NUMBER, 1), number(TRACK_UID, 1), number(TRACK_TYPE, 2), number(FLAG_LACING, 1), number(DEFAULT_DURATION, UNIT * 10**9 // RATE), element(CODEC_ID, b"A_PCM/INT/LIT"), element(AUDIO, element(SAMPLING_FREQUENCY, struct.pack(">d", RATE)) + number(CHANNELS, 1) + number(BIT_DEPTH, 8))])
    return element(TRACKS, element(TRACK_ENTRY, track))


def mux(payload: bytes) -> bytes:
    """``payload`` (a multiple of ``UNIT`` bytes) as packets of one 8-bit PCM track; the three lacings take turns."""
    step = UNIT * 1000 // RATE  # milliseconds a packet
    frames = [payload[a : a + UNIT] for a in range(0, len(payload), UNIT)]
    header = element(EBML, b"".join([number(EBML_VERSION, 1), number(EBML_READ_VERSION, 1), number(EBML_MAX_ID, 4), number(EBML_MAX_SIZE, 8), element(DOC_TYPE, b"matroska"), number(DOC_TYPE_VERSION, 4), number(DOC_TYPE_READ, 2)]))
    info = element(INFO, number(TIMESTAMP_SCALE, 1_000_000) + element(DURATION, struct.pack(">d", step * len(frames))) + element(MUXING_APP, b"gossamer") + element(WRITING_APP, b"gossamer"))
    body, at, cues = [info, _head()], len(info) + len(_head()), []
    span = PACKETS_A_BLOCK * BLOCKS_A_CLUSTER
    for first in range(0, len(frames), span):
        inside = [number(TIMESTAMP, first * step)]
        for k, a in enumerate(range(first, min(first + span, len(frames)), PACKETS_A_BLOCK)):
            own = frames[a : min(a + PACKETS_A_BLOCK, first + span)]
            mode = (2, 3, 1)[k % 3] if len(own) > 1 else 0
            packed = lace(own, mode) if mode else own[0]
            head = b"\x81" + struct.pack(">h", (a - first) * step)
            if k % 4 == 3:
                inside.append(element(BLOCK_GROUP, element(BLOCK, head + bytes([mode << 1]) + packed) + number(BLOCK_DURATION, step * len(own))))
            else:
                inside.append(element(SIMPLE_BLOCK, head + bytes([128 | mode << 1]) + packed))
        cluster = element(CLUSTER, b"".join(inside))
        cues.append(element(CUE_POINT, number(CUE_TIME, first * step) + element(CUE_TRACK_POSITIONS, number(CUE_TRACK, 1) + number(CUE_CLUSTER_POSITION, at))))
        body.append(cluster)
        at += len(cluster)
    body.append(element(CUES, b"".join(cues)))
    return header + element(SEGMENT, b"".join(body), 8)


# --- columns ------------------------------------------------------------------------------------------


def padded(text: str) -> bytes:
    raw = text.encode("utf-8", "surrogatepass")
    return raw + b" " * (max(1, -(-len(raw) // UNIT)) * UNIT - len(raw))


def store(docs: DataFrame) -> DataFrame:
    """``doc_id, n_bytes, media``: each whole text as a Matroska file."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in common.slices(batches):
            many = part.column(1).to_pylist()
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(t.encode("utf-8", "surrogatepass")) for t in many], pa.int64()), pa.array([mux(padded(t)) for t in many], pa.binary())], ["doc_id", "n_bytes", "media"])

    return common.texts(docs).mapInArrow(run, "doc_id long, n_bytes long, media binary")


def packet_table(files: DataFrame, key: str = "doc_id", media: str = "media") -> DataFrame:
    """One row a packet: ``key, packet, track, codec, timestamp_ns, offset, size, keyframe``."""
    names = [key, "packet", "track", "codec", "timestamp_ns", "offset", "size", "keyframe"]
    kinds = (pa.int64(), pa.int64(), pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.bool_())

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in common.slices(batches, media):
            for who, data in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                try:
                    movie = parse(data or b"")
                except ValueError:
                    continue
                rows = [(who, i, p.track, movie.tracks.get(p.track, {}).get("codec"), p.timestamp * movie.scale, p.offset, p.size, p.keyframe) for i, p in enumerate(movie.packets)]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(x, type=t) for x, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    return files.select(F.col(key).cast("long").alias(key), F.col(media)).mapInArrow(run, f"`{key}` long, packet long, track int, codec string, timestamp_ns long, offset long, size long, keyframe boolean")


def features(files: DataFrame, media: str = "media") -> DataFrame:
    """Reads the stored files back: payload and packet figures of each ``(doc_id, n_bytes, media)``."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in common.slices(batches, media):
            rows = []
            for doc_id, n_bytes, data in zip(*[part.column(k).to_pylist() for k in range(3)], strict=True):
                movie = parse(data)
                payload = b"".join([data[p.offset : p.offset + p.size] for p in movie.packets])
                cued = sum(movie.segment_at + at + 4 <= c <= movie.segment_at + at + 12 for (_, _, at), c in zip(movie.cues, movie.clusters, strict=False))
                say = {"tracks": len(movie.tracks), "packets": len(movie.packets), "clusters": len(movie.clusters), "cues": cued, "laced": "/".join(map(str, movie.laced)), "keyframes": sum(p.keyframe for p in movie.packets), "last_ms": movie.packets[-1].timestamp * movie.scale // 10**6, "first_at": movie.packets[0].offset}
                rows.append((doc_id, n_bytes, len(payload), hashlib.sha256(payload).hexdigest(), crc32(payload[-16:]), len(data), hashlib.sha256(data).hexdigest(), ";".join(f"{k}={v}" for k, v in say.items())))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string())
            yield pa.RecordBatch.from_arrays([pa.array(x, type=t) for x, t in zip(zip(*rows, strict=True), kinds, strict=True)], ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return files.select("doc_id", "n_bytes", media).mapInArrow(run, schema)
