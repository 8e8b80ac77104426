"""Matroska media columns: a reader of EBML trees, clusters, lacing and cues, and a writer for lossless byte tracks."""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# fixed values: element ids of the Matroska format
EBML, SEGMENT, INFO, TRACKS, CLUSTER, CUES = 0x1A45DFA3, 0x18538067, 0x1549A966, 0x1654AE6B, 0x1F43B675, 0x1C53BB6B
SEEK_HEAD, TAGS, CHAPTERS, ATTACHMENTS = 0x114D9B74, 0x1254C367, 0x1043A770, 0x1941A469
DOC_TYPE, DOC_TYPE_VERSION, DOC_TYPE_READ_VERSION = 0x4282, 0x4287, 0x4285
EBML_VERSION, EBML_READ_VERSION, EBML_MAX_ID, EBML_MAX_SIZE = 0x4286, 0x42F7, 0x42F2, 0x42F3
TIMESTAMP_SCALE, DURATION, MUXING_APP, WRITING_APP = 0x2AD7B1, 0x4489, 0x4D80, 0x5741
TRACK_ENTRY, TRACK_NUMBER, TRACK_UID, TRACK_TYPE, FLAG_LACING, CODEC_ID, DEFAULT_DURATION = 0xAE, 0xD7, 0x73C5, 0x83, 0x9C, 0x86, 0x23E383
AUDIO, SAMPLING_FREQUENCY, CHANNELS, BIT_DEPTH = 0xE1, 0xB5, 0x9F, 0x6264
CLUSTER_TIMESTAMP, SIMPLE_BLOCK, BLOCK_GROUP, BLOCK, BLOCK_DURATION = 0xE7, 0xA3, 0xA0, 0xA1, 0x9B
CUE_POINT, CUE_TIME, CUE_TRACK_POSITIONS, CUE_TRACK, CUE_CLUSTER_POSITION = 0xBB, 0xB3, 0xB7, 0xF7, 0xF1
TOP = {INFO, TRACKS, CLUSTER, CUES, SEEK_HEAD, TAGS, CHAPTERS, ATTACHMENTS}

PACKETS = "track int, packet long, timestamp_ns long, byte_start long, byte_length long, keyframe boolean, cluster int, lacing string"


class BadMedia(ValueError):
    """Bytes that do not follow the format."""


def read_vint(data: bytes, at: int, keep_marker: bool = False) -> tuple[int, int, bool]:
    """Value, next position, and whether all value bits are set (an unknown size)."""
    if at >= len(data) or not data[at]:
        raise BadMedia(f"no variable-length integer at {at}")
    width = 9 - data[at].bit_length()
    if at + width > len(data):
        raise BadMedia(f"integer cut off at {at}")
    raw = int.from_bytes(data[at : at + width], "big")
    value = raw & ((1 << 7 * width) - 1)
    return raw if keep_marker else value, at + width, value == (1 << 7 * width) - 1


def write_vint(value: int, width: int = 0) -> bytes:
    """Shortest size field (or of a given width); the all-ones value of a width is reserved."""
    width = width or next(w for w in range(1, 9) if value < (1 << 7 * w) - 1)
    return (value | 1 << 7 * width).to_bytes(width, "big")


def elements(data: bytes, at: int, end: int):
    """(id, payload start, payload end) of the elements in [at, end); an unknown size reaches to the next sibling or end."""
    while at < end:
        kind, at, _ = read_vint(data, at, True)
        size, at, unknown = read_vint(data, at)
        stop = _open_end(data, at, end, kind) if unknown else at + size
        if stop > end:
            raise BadMedia(f"element {kind:x} leaves its parent at {at}")
        yield kind, at, stop
        at = stop


def _open_end(data: bytes, at: int, end: int, kind: int) -> int:
    if kind != CLUSTER:
        return end
    while at < end:
        inner, start, _ = read_vint(data, at, True)
        if inner in TOP:
            return at
        size, start, unknown = read_vint(data, start)
        if unknown:
            raise BadMedia("unknown size inside a cluster")
        at = start + size
    return end


def _uint(data: bytes, a: int, b: int) -> int:
    return int.from_bytes(data[a:b], "big")


def _float(data: bytes, a: int, b: int) -> float:
    return {0: lambda: 0.0, 4: lambda: struct.unpack(">f", data[a:b])[0], 8: lambda: struct.unpack(">d", data[a:b])[0]}[b - a]()


LACINGS = ("none", "xiph", "fixed", "ebml")


def block_frames(data: bytes, at: int, end: int) -> tuple[int, int, bool, str, list[tuple[int, int]]]:
    """Track, relative timestamp, key flag, lacing and the byte ranges of a block's frames."""
    track, at, _ = read_vint(data, at)
    if at + 3 > end:
        raise BadMedia("block header cut off")
    ticks, flags = struct.unpack_from(">hB", data, at)
    at += 3
    lacing = flags >> 1 & 3
    if not lacing:
        return track, ticks, bool(flags & 0x80), "none", [(at, end - at)]
    if at >= end:
        raise BadMedia("lace count missing")
    n = data[at] + 1
    at += 1
    sizes: list[int] = []
    if lacing == 1:
        for _ in range(n - 1):
            size = 0
            while True:
                if at >= end:
                    raise BadMedia("lace sizes cut off")
                size += data[at]
                at += 1
                if data[at - 1] != 255:
                    break
            sizes.append(size)
    elif lacing == 3 and n > 1:
        size, at, _ = read_vint(data, at)
        sizes.append(size)
        for _ in range(n - 2):
            before = at
            raw, at, _ = read_vint(data, at)
            size += raw - ((1 << (7 * (at - before) - 1)) - 1)
            sizes.append(size)
    if lacing == 2:
        if (end - at) % n:
            raise BadMedia("fixed lacing does not divide the block")
        sizes = [(end - at) // n] * n
    else:
        sizes.append(end - at - sum(sizes))
    if min(sizes) < 0 or sum(sizes) != end - at:
        raise BadMedia("lace sizes do not fit the block")
    frames = []
    for size in sizes:
        frames.append((at, size))
        at += size
    return track, ticks, bool(flags & 0x80), LACINGS[lacing], frames


def parse_matroska(data: bytes) -> dict:
    """Tracks, packets in file order and cues of a Matroska file. Raises BadMedia."""
    out: dict = {"doc_type": "", "scale": 1_000_000, "tracks": {}, "packets": [], "cues": [], "clusters": [], "duration": 0.0}
    for kind, a, b in elements(data, 0, len(data)):
        if kind == EBML:
            out["doc_type"] = next((data[x:y].rstrip(b"\0").decode("latin-1") for k, x, y in elements(data, a, b) if k == DOC_TYPE), "")
        elif kind == SEGMENT:
            _segment(data, a, b, out)
    if out["doc_type"] not in ("matroska", "webm"):
        raise BadMedia("not a Matroska file")
    return out


def _segment(data: bytes, a: int, b: int, out: dict) -> None:
    base = a
    for kind, a, b in elements(data, a, b):
        if kind == INFO:
            for k, x, y in elements(data, a, b):
                if k == TIMESTAMP_SCALE:
                    out["scale"] = _uint(data, x, y)
                elif k == DURATION:
                    out["duration"] = _float(data, x, y)
        elif kind == TRACKS:
            for k, x, y in elements(data, a, b):
                if k == TRACK_ENTRY:
                    t = {"number": 0, "type": 0, "codec": "", "rate": 8000.0, "channels": 1, "bits": 0, "frame_ns": 0}
                    for j, p, q in elements(data, x, y):
                        if j == TRACK_NUMBER:
                            t["number"] = _uint(data, p, q)
                        elif j == TRACK_TYPE:
                            t["type"] = _uint(data, p, q)
                        elif j == CODEC_ID:
                            t["codec"] = data[p:q].rstrip(b"\0").decode("latin-1")
                        elif j == DEFAULT_DURATION:
                            t["frame_ns"] = _uint(data, p, q)
                        elif j == AUDIO:
                            for i, v, w in elements(data, p, q):
                                if i == SAMPLING_FREQUENCY:
                                    t["rate"] = _float(data, v, w)
                                elif i == CHANNELS:
                                    t["channels"] = _uint(data, v, w)
                                elif i == BIT_DEPTH:
                                    t["bits"] = _uint(data, v, w)
                    out["tracks"][t["number"]] = t
        elif kind == CLUSTER:
            ticks, number = 0, len(out["clusters"])
            out["clusters"].append(a - base)
            for k, x, y in elements(data, a, b):
                if k == CLUSTER_TIMESTAMP:
                    ticks = _uint(data, x, y)
                elif k == SIMPLE_BLOCK:
                    _block(data, x, y, ticks, number, out, None)
                elif k == BLOCK_GROUP:
                    inner = {j: (p, q) for j, p, q in elements(data, x, y)}
                    if BLOCK in inner:
                        _block(data, *inner[BLOCK], ticks, number, out, 0xFB not in inner)
        elif kind == CUES:
            for k, x, y in elements(data, a, b):
                if k == CUE_POINT:
                    cue = {"time": 0, "track": 0, "position": 0}
                    for j, p, q in elements(data, x, y):
                        if j == CUE_TIME:
                            cue["time"] = _uint(data, p, q)
                        elif j == CUE_TRACK_POSITIONS:
                            for i, v, w in elements(data, p, q):
                                if i == CUE_TRACK:
                                    cue["track"] = _uint(data, v, w)
                                elif i == CUE_CLUSTER_POSITION:
                                    cue["position"] = base + _uint(data, v, w)
                    out["cues"].append(cue)


def _block(data, a, b, ticks, cluster, out, key) -> None:
    track, relative, flag, lacing, frames = block_frames(data, a, b)
    step = out["tracks"].get(track, {}).get("frame_ns", 0)
    for i, (start, size) in enumerate(frames):
        out["packets"].append((track, len(out["packets"]), (ticks + relative) * out["scale"] + i * step, start, size, flag if key is None else key, cluster, lacing))


def _element(kind: int, payload: bytes) -> bytes:
    return kind.to_bytes((kind.bit_length() + 7) // 8, "big") + write_vint(len(payload)) + payload


def _number(kind: int, value: int) -> bytes:
    return _element(kind, value.to_bytes(max(1, (value.bit_length() + 7) // 8), "big"))


FRAME, LACED, PER_CLUSTER = 512, 8, 16  # bytes of a frame, frames of a block, blocks of a cluster
RATE = 8000


def _laced(frames: list[bytes], ticks: int, lacing: int) -> bytes:
    """A key SimpleBlock of track 1."""
    if len(frames) == 1:
        lacing = 0
    if lacing == 2 and len({len(f) for f in frames}) > 1:
        lacing = 3
    head = b"\x81" + struct.pack(">hB", ticks, 0x80 | lacing << 1)
    if lacing:
        head += bytes([len(frames) - 1])
    sizes = [len(f) for f in frames]
    if lacing == 1:
        head += b"".join(b"\xff" * (s // 255) + bytes([s % 255]) for s in sizes[:-1])
    elif lacing == 3:
        head += write_vint(sizes[0])
        for x, y in zip(sizes, sizes[1:-1]):
            width = next(w for w in range(1, 9) if abs(y - x) < (1 << 7 * w - 1) - 1)
            head += write_vint(y - x + (1 << 7 * width - 1) - 1, width)
    return _element(SIMPLE_BLOCK, head + b"".join(frames))


def write_matroska(payload: bytes) -> bytes:
    """Mux bytes as unsigned 8-bit mono samples at 8 kHz: frames of 512, laced by eights in all the ways there are."""
    header = _element(EBML, _number(EBML_VERSION, 1) + _number(EBML_READ_VERSION, 1) + _number(EBML_MAX_ID, 4) + _number(EBML_MAX_SIZE, 8) + _element(DOC_TYPE, b"matroska") + _number(DOC_TYPE_VERSION, 4) + _number(DOC_TYPE_READ_VERSION, 2))
    info = _element(INFO, _number(TIMESTAMP_SCALE, 1_000_000) + _element(DURATION, struct.pack(">d", len(payload) * 1000 / RATE)) + _element(MUXING_APP, b"graphslice") + _element(WRITING_APP, b"graphslice"))
    audio = _element(AUDIO, _element(SAMPLING_FREQUENCY, struct.pack(">d", RATE)) + _number(CHANNELS, 1) + _number(BIT_DEPTH, 8))
    tracks = _element(TRACKS, _element(TRACK_ENTRY, _number(TRACK_NUMBER, 1) + _number(TRACK_UID, 1) + _number(TRACK_TYPE, 2) + _number(FLAG_LACING, 1) + _number(DEFAULT_DURATION, FRAME * 1_000_000_000 // RATE) + _element(CODEC_ID, b"A_PCM/INT/LIT") + audio))
    body, cues, at = [info, tracks], [], len(info) + len(tracks)
    span, per_frame = FRAME * LACED * PER_CLUSTER, FRAME * 1000 // RATE
    for first in range(0, len(payload), span):
        inner = [_number(CLUSTER_TIMESTAMP, first // FRAME * per_frame)]
        for number, start in enumerate(range(first, min(first + span, len(payload)), FRAME * LACED)):
            piece = payload[start : min(start + FRAME * LACED, first + span)]
            inner.append(_laced([piece[i : i + FRAME] for i in range(0, len(piece), FRAME)], (start - first) // FRAME * per_frame, (number + first // span) % 3 + 1))
        cluster = _element(CLUSTER, b"".join(inner))
        cues.append(_element(CUE_POINT, _number(CUE_TIME, first // FRAME * per_frame) + _element(CUE_TRACK_POSITIONS, _number(CUE_TRACK, 1) + _number(CUE_CLUSTER_POSITION, at))))
        body.append(cluster)
        at += len(cluster)
    body.append(_element(CUES, b"".join(cues)))
    return header + _element(SEGMENT, b"".join(body))


def packet_table(media: DataFrame, key: str, content: str) -> DataFrame:
    """One row per packet of each file: key, the packet columns, and `error` (null unless the bytes are malformed).

    A null, empty or malformed file gives one row with null packet columns and the reason. Repeated rows give repeated
    packets; other columns are not carried.
    """
    kind = media.schema[key].dataType.simpleString()
    typed = pa.schema([("k", {"bigint": pa.int64(), "int": pa.int32(), "string": pa.string()}[kind]), ("track", pa.int32()), ("packet", pa.int64()), ("timestamp_ns", pa.int64()), ("byte_start", pa.int64()), ("byte_length", pa.int64()), ("keyframe", pa.bool_()), ("cluster", pa.int32()), ("lacing", pa.string()), ("error", pa.string())])

    def parse(batches):
        for batch in batches:
            rows = []
            for k, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                try:
                    found = parse_matroska(data or b"")["packets"]
                    rows += [(k, *p, None) for p in found] or [(k, *[None] * 8, "no packets")]
                except BadMedia as e:
                    rows.append((k, *[None] * 8, str(e)))
                if len(rows) > 20_000:
                    yield _batch(rows, typed)
                    rows = []
            if rows:
                yield _batch(rows, typed)

    return media.select(F.col(key), F.col(content)).mapInArrow(parse, f"k {kind}, {PACKETS}, error string").withColumnRenamed("k", key)


def _batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), schema)], schema=schema)


def pad64(data: bytes) -> bytes:
    """Zero bytes up to a positive multiple of 64."""
    return data + b"\0" * (64 if not data else -len(data) % 64)


_DIGEST = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string())])


def _digest(text: str | None) -> tuple:
    raw = (text or "").encode()
    media = write_matroska(pad64(raw))
    parsed = parse_matroska(media)
    back = b"".join([media[p[3] : p[3] + p[4]] for p in parsed["packets"]])
    samples = np.frombuffer(back, np.uint8)
    last = parsed["packets"][-1]
    level = int(samples.sum(dtype=np.int64)) * 1000 // len(samples)
    turns = int(np.count_nonzero((samples[1:] >= 128) != (samples[:-1] >= 128)))
    feature = f"tracks={len(parsed['tracks'])};packets={len(parsed['packets'])};clusters={len(parsed['clusters'])};cues={len(parsed['cues'])};last_ns={last[2]};mean_milli={level};crossings={turns};peak={int(samples.max())}"
    return len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(media), hashlib.sha256(media).hexdigest(), feature


def text_media_digest(docs: DataFrame) -> DataFrame:
    """Each whole text (null: empty) muxed, parsed back and measured; one row per input row, no shuffle.

    Equal texts give equal values; repeated rows stay repeated; other columns are not carried.
    """

    def run(batches):
        for batch in batches:
            ids, texts = batch.column(0), batch.column(1)
            for i in range(0, len(ids), 512):
                rows = [(k, *_digest(t)) for k, t in zip(ids[i : i + 512].to_pylist(), texts[i : i + 512].to_pylist())]
                yield _batch(rows, _DIGEST)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")
