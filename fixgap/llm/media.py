"""Media columns in Matroska: documents are stored as 8-bit PCM tracks and read back through a packet table.

The container is EBML: every element is a variable-length id, a variable-length size, and a payload. `mux` writes
header, track, clusters of laced SimpleBlocks and cues; `packets` parses any file made of these elements (all four
lacings, BlockGroups, unknown-sized segments and clusters) into packets with timestamp, track and byte range. A lace's frames
are a default duration of their track apart; without one they all have their block's timestamp.

The query writes the files as a media column of a table in the shared folder; from there they are parsed into a packet column,
the nested form of the packet table, and the payload is read back by the packets' byte ranges.

Nulls: a null text is empty. An empty text gives one unit of 64 zero bytes. Long texts take as many clusters as needed.
Repeated rows stay, each with equal values; extra columns are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .base import materialise

# Fixed values of the format: element ids.
EBML, SEGMENT, INFO, TRACKS, CLUSTER, CUES = 0x1A45DFA3, 0x18538067, 0x1549A966, 0x1654AE6B, 0x1F43B675, 0x1C53BB6B
EBML_VERSION, EBML_READ_VERSION, MAX_ID, MAX_SIZE, DOC_TYPE, DOC_VERSION, DOC_READ = 0x4286, 0x42F7, 0x42F2, 0x42F3, 0x4282, 0x4287, 0x4285
TIME_SCALE, DURATION, MUXER, WRITER = 0x2AD7B1, 0x4489, 0x4D80, 0x5741
TRACK_ENTRY, TRACK_NUMBER, TRACK_UID, TRACK_TYPE, FLAG_LACING, FRAME_TIME, CODEC, AUDIO, RATE, CHANNELS, DEPTH = 0xAE, 0xD7, 0x73C5, 0x83, 0x9C, 0x23E383, 0x86, 0xE1, 0xB5, 0x9F, 0x6264
CLUSTER_TIME, SIMPLE_BLOCK, BLOCK_GROUP, BLOCK = 0xE7, 0xA3, 0xA0, 0xA1
CUE_POINT, CUE_TIME, CUE_POSITIONS, CUE_TRACK, CUE_CLUSTER = 0xBB, 0xB3, 0xB7, 0xF7, 0xF1

UNIT = 64  # payloads are padded to a multiple of this
SAMPLE_RATE = 8000  # one byte a sample, so UNIT bytes are exactly 8 ms
FRAME = 512  # bytes of one packet
FRAMES_PER_BLOCK, BLOCKS_PER_CLUSTER = 8, 8


def size_vint(n: int) -> bytes:
    """A size in the fewest bytes; all-ones is kept for 'unknown'."""
    width = 1
    while n >= (1 << 7 * width) - 1:
        width += 1
    return ((1 << 7 * width) | n).to_bytes(width, "big")


def read_vint(data: bytes, at: int, keep_marker: bool = False) -> tuple[int | None, int]:
    """Value and next offset; None for the reserved all-ones size."""
    first = data[at]
    if not first:
        raise ValueError(f"no length marker at byte {at}")
    width = 9 - first.bit_length()
    raw = int.from_bytes(data[at : at + width], "big")
    if keep_marker:
        return raw, at + width
    value = raw & ((1 << 7 * width) - 1)
    return (None if value == (1 << 7 * width) - 1 else value), at + width


def element(kind: int, payload: bytes) -> bytes:
    return kind.to_bytes((kind.bit_length() + 7) // 8, "big") + size_vint(len(payload)) + payload


def uint(kind: int, n: int) -> bytes:
    return element(kind, n.to_bytes(max(1, (n.bit_length() + 7) // 8), "big"))


def laced(sizes: list[int]) -> tuple[int, bytes]:
    """Lacing flag bits and lace header: none for one frame, fixed for equal sizes, else EBML lacing."""
    if len(sizes) == 1:
        return 0, b""
    if len(set(sizes)) == 1:
        return 0x04, bytes([len(sizes) - 1])
    head = bytes([len(sizes) - 1]) + size_vint(sizes[0])
    for a, b in zip(sizes[:-2], sizes[1:-1], strict=True):
        head += _signed_vint(b - a)
    return 0x06, head


def _signed_vint(n: int) -> bytes:
    width = 1
    while abs(n) >= (1 << (7 * width - 1)) - 1:
        width += 1
    return ((1 << 7 * width) | (n + (1 << (7 * width - 1)) - 1)).to_bytes(width, "big")


_HEADER = element(EBML, uint(EBML_VERSION, 1) + uint(EBML_READ_VERSION, 1) + uint(MAX_ID, 4) + uint(MAX_SIZE, 8) + element(DOC_TYPE, b"matroska") + uint(DOC_VERSION, 4) + uint(DOC_READ, 2))
_TRACK = element(
    TRACKS,
    element(
        TRACK_ENTRY,
        uint(TRACK_NUMBER, 1) + uint(TRACK_UID, 1) + uint(TRACK_TYPE, 2) + uint(FLAG_LACING, 1) + uint(FRAME_TIME, FRAME * 1_000_000_000 // SAMPLE_RATE) + element(CODEC, b"A_PCM/INT/LIT")
        + element(AUDIO, element(RATE, struct.pack(">d", SAMPLE_RATE)) + uint(CHANNELS, 1) + uint(DEPTH, 8)),
    ),
)


def mux(payload: bytes) -> bytes:
    """A Matroska file with the payload as one 8-bit PCM track. Timestamps count milliseconds."""
    ms = lambda n: n * 1000 // SAMPLE_RATE
    info = element(INFO, uint(TIME_SCALE, 1_000_000) + element(DURATION, struct.pack(">d", ms(len(payload)))) + element(MUXER, b"fixgap") + element(WRITER, b"fixgap"))
    body, cues = [info, _TRACK], []
    at = len(info) + len(_TRACK)
    per_block = FRAME * FRAMES_PER_BLOCK
    for start in range(0, len(payload), per_block * BLOCKS_PER_CLUSTER):
        time, parts = ms(start), [uint(CLUSTER_TIME, ms(start))]
        for b in range(start, min(start + per_block * BLOCKS_PER_CLUSTER, len(payload)), per_block):
            chunk = payload[b : b + per_block]
            sizes = [min(FRAME, len(chunk) - i) for i in range(0, len(chunk), FRAME)]
            flag, head = laced(sizes)
            parts.append(element(SIMPLE_BLOCK, b"\x81" + struct.pack(">hB", ms(b) - time, 0x80 | flag) + head + chunk))
        cluster = element(CLUSTER, b"".join(parts))
        cues.append(element(CUE_POINT, uint(CUE_TIME, time) + element(CUE_POSITIONS, uint(CUE_TRACK, 1) + uint(CUE_CLUSTER, at))))
        body.append(cluster)
        at += len(cluster)
    return _HEADER + element(SEGMENT, b"".join([*body, element(CUES, b"".join(cues))]))


def elements(data: bytes, start: int, end: int) -> Iterator[tuple[int, int, int]]:
    """(id, payload start, payload end) of the elements in a byte range; an unknown size reaches to the next element of the parent's level, or the end."""
    at = start
    while at < end:
        kind, at = read_vint(data, at, keep_marker=True)
        size, at = read_vint(data, at)
        stop = _unknown_end(data, kind, at, end) if size is None else at + size
        if stop > end:
            raise ValueError(f"element {kind:#x} at byte {at} is cut off")
        yield kind, at, stop
        at = stop


def _unknown_end(data: bytes, kind: int, at: int, end: int) -> int:
    """An unknown-sized cluster ends before the next top-level element; any other reaches the end of its parent."""
    while kind == CLUSTER and at < end:
        child, body = read_vint(data, at, keep_marker=True)
        if child in (CLUSTER, CUES, INFO, TRACKS):
            return at
        size, body = read_vint(data, body)
        at = body + size
    return end


def frame_sizes(data: bytes, flag: int, at: int, end: int) -> tuple[list[int], int]:
    """Sizes of a block's frames and the offset of the first."""
    lacing = flag >> 1 & 3
    if not lacing:
        return [end - at], at
    n, at = data[at] + 1, at + 1
    if lacing == 2:
        return [(end - at) // n] * n, at
    sizes: list[int] = []
    for _ in range(n - 1):
        if lacing == 1:
            size = 0
            while True:
                size, at = size + data[at], at + 1
                if data[at - 1] != 255:
                    break
        else:
            width = 9 - data[at].bit_length()
            value, at = read_vint(data, at)
            value = (1 << 7 * width) - 1 if value is None else value
            size = value if not sizes else sizes[-1] + value - ((1 << (7 * width - 1)) - 1)
        sizes.append(size)
    return [*sizes, end - at - sum(sizes)], at


def packets(data: bytes) -> dict[str, list]:
    """Parallel lists: track, timestamp (in the file's time scale), frame (number in the block), offset, size, keyframe; and the cues and cluster offsets."""
    out: dict[str, list] = {k: [] for k in ("track", "timestamp", "frame", "offset", "size", "keyframe", "clusters", "cues")}
    scale, durations = 1_000_000, {}  # nanoseconds of a unit of time, and of a frame of each track
    number = lambda x, y: int.from_bytes(data[x:y], "big")
    for kind, a, b in elements(data, 0, len(data)):
        if kind != SEGMENT:
            continue
        base = a
        for inner, c, d in elements(data, a, b):
            if inner == CLUSTER:
                out["clusters"].append(base)
                _cluster(data, c, d, out, {k: v / scale for k, v in durations.items()})
            elif inner == INFO:
                scale = next((number(x, y) for k, x, y in elements(data, c, d) if k == TIME_SCALE), scale)
            elif inner == TRACKS:
                for _, e, f in elements(data, c, d):
                    entry = {k: (x, y) for k, x, y in elements(data, e, f)}
                    if TRACK_NUMBER in entry and FRAME_TIME in entry:
                        durations[number(*entry[TRACK_NUMBER])] = number(*entry[FRAME_TIME])
            elif inner == CUES:
                for _, e, f in elements(data, c, d):
                    entry = {k: (x, y) for k, x, y in elements(data, e, f)}
                    where = {k: number(x, y) for k, x, y in elements(data, *entry[CUE_POSITIONS])}
                    out["cues"].append((number(*entry[CUE_TIME]), where[CUE_TRACK], a + where[CUE_CLUSTER]))
            base = d
    return out


def _cluster(data: bytes, c: int, d: int, out: dict[str, list], apart: dict[int, float]) -> None:
    time = 0
    for kind, e, f in elements(data, c, d):
        if kind == CLUSTER_TIME:
            time = int.from_bytes(data[e:f], "big")
            continue
        if kind == BLOCK_GROUP:
            e, f = next(((x, y) for k, x, y in elements(data, e, f) if k == BLOCK), (0, 0))
        elif kind != SIMPLE_BLOCK:
            continue
        if e == f:
            continue
        track, at = read_vint(data, e)
        shift, flag = struct.unpack_from(">hB", data, at)
        sizes, at = frame_sizes(data, flag, at + 3, f)
        for i, size in enumerate(sizes):
            for k, v in (("track", track), ("timestamp", time + shift + round(i * apart.get(track, 0))), ("frame", i), ("offset", at), ("size", size), ("keyframe", bool(flag & 0x80))):
                out[k].append(v)
            at += size


def payload_of(text: bytes) -> bytes:
    return text + bytes(-len(text) % UNIT or (0 if text else UNIT))


def features(packets_: list[dict], clusters: int, cues: int, payload: bytes) -> str:
    x = np.frombuffer(payload, np.uint8)
    counts = np.bincount(x, minlength=256)
    p = counts[counts > 0] / len(x)
    last = packets_[-1]["timestamp_ms"] if packets_ else 0
    return f"packets={len(packets_)};clusters={clusters};cues={cues};last_ms={last};mean={x.mean():.4f};rms={np.sqrt((counts * np.arange(256.0) ** 2).sum() / len(x)):.4f};entropy={-(p * np.log2(p)).sum():.4f}"


def store(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, media (binary): each text as a Matroska file."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for some in _slices(b):
                texts = [x or b"" for x in some.column("raw").to_pylist()]
                yield pa.RecordBatch.from_arrays([some.column("doc_id"), pa.array(map(len, texts), pa.int64()), pa.array([mux(payload_of(x)) for x in texts], pa.binary())], names=["doc_id", "n_bytes", "media"])

    raw = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").cast("binary").alias("raw"))
    return raw.mapInArrow(run, "doc_id long, n_bytes long, media binary")


def _slices(b: pa.RecordBatch, rows: int = 500) -> Iterator[pa.RecordBatch]:
    """A batch in parts, so that what is made of it stays small."""
    return (b.slice(i, rows) for i in range(0, b.num_rows, rows))


_PACKET = ["track", "timestamp_ms", "frame", "byte_offset", "byte_size", "keyframe"]
PACKETS = "array<struct<track:long,timestamp_ms:long,frame:long,byte_offset:long,byte_size:long,keyframe:boolean>>"
_PACKETS = pa.list_(pa.struct([(k, pa.int64()) for k in _PACKET[:-1]] + [(_PACKET[-1], pa.bool_())]))


def with_packets(media: DataFrame) -> DataFrame:
    """A media table with its files parsed: packets, cues (time, track, offset of the cluster) and clusters (offsets)."""
    kinds = {"packets": _PACKETS, "cues": pa.list_(pa.struct([(k, pa.int64()) for k in ("time", "track", "byte_offset")])), "clusters": pa.list_(pa.int64())}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for some in _slices(b):
                found = [packets(x) for x in some.column("media").to_pylist()]
                rows = [[dict(zip(_PACKET, r, strict=True)) for r in zip(*(p[k] for k in ("track", "timestamp", "frame", "offset", "size", "keyframe")), strict=True)] for p in found]
                cues = [[{"time": t, "track": k, "byte_offset": o} for t, k, o in p["cues"]] for p in found]
                new = (rows, cues, [p["clusters"] for p in found])
                yield pa.RecordBatch.from_arrays([*some.columns, *(pa.array(c, k) for c, k in zip(new, kinds.values(), strict=True))], names=[*some.schema.names, *kinds])

    more = T.StructType.fromDDL(f"packets {PACKETS}, cues array<struct<time:long,track:long,byte_offset:long>>, clusters array<long>")
    return media.mapInArrow(run, T.StructType([*media.schema.fields, *more.fields]))


def packet_table(media: DataFrame) -> DataFrame:
    """One row for each packet of each file: doc_id, track, timestamp_ms, frame, byte_offset, byte_size, keyframe."""
    return with_packets(media.select("doc_id", "media")).select("doc_id", F.explode("packets").alias("p")).select("doc_id", "p.*")


def described(parsed: DataFrame) -> DataFrame:
    """Payloads read back by the packets' byte ranges, and both forms described."""
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[tuple] = []
            for doc, n, media, found, cues, clusters in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "n_bytes", "media", "packets", "n_cues", "n_clusters")), strict=True):
                back = b"".join([media[p["byte_offset"] : p["byte_offset"] + p["byte_size"]] for p in found])
                rows.append((doc, n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-UNIT:]), len(media), hashlib.sha256(media).hexdigest(), features(found, clusters, cues, back)))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 8
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=names)

    some = parsed.select("doc_id", "n_bytes", "media", "packets", F.size("cues").alias("n_cues"), F.size("clusters").alias("n_clusters"))
    return some.mapInArrow(run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


def digests(docs: DataFrame) -> DataFrame:
    """Write each text's file to a table, parse the stored files into packets, read the payloads back, and describe both forms."""
    return described(with_packets(materialise(store(docs), "media")))
