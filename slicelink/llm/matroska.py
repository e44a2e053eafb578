"""Matroska containers: a writer for 8-bit PCM payloads and a general parser into packet tables.

The parser reads variable-length EBML elements (also of unknown size), tracks, clusters, block groups and simple
blocks, the three kinds of lacing and the cues, and gives one packet per frame: track, timestamp in nanoseconds, byte
range in the file, key flag. The writer puts a payload into frames of `FRAME` samples, several to a laced block,
clusters of some seconds and a cue for each.

Defined results: null text is an empty one; a payload has one frame at least; equal texts give equal bytes and
values; an empty table gives no rows; further columns are ignored. Bytes that break off end the packet list there.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa

from .common import raw, ready, slices, table

FRAME, RATE = 576, 8000
# fixed values: element ids of the container format
EBML, VERSION, READ_VERSION, MAX_ID, MAX_SIZE, DOC_TYPE, DOC_VERSION, DOC_READ = 0x1A45DFA3, 0x4286, 0x42F7, 0x42F2, 0x42F3, 0x4282, 0x4287, 0x4285
SEGMENT, INFO, SCALE, DURATION, MUXER, WRITER = 0x18538067, 0x1549A966, 0x2AD7B1, 0x4489, 0x4D80, 0x5741
TRACKS, ENTRY, NUMBER, UID, TYPE, CODEC, DEFAULT_DURATION, AUDIO, FREQUENCY, CHANNELS, DEPTH, LACED = 0x1654AE6B, 0xAE, 0xD7, 0x73C5, 0x83, 0x86, 0x23E383, 0xE1, 0xB5, 0x9F, 0x6264, 0x9C
CLUSTER, TIMECODE, SIMPLE, GROUP, BLOCK, REFERENCE = 0x1F43B675, 0xE7, 0xA3, 0xA0, 0xA1, 0xFB
CUES, POINT, CUE_TIME, POSITIONS, CUE_TRACK, CUE_CLUSTER = 0x1C53BB6B, 0xBB, 0xB3, 0xB7, 0xF7, 0xF1
PARENTS = {SEGMENT, INFO, TRACKS, ENTRY, AUDIO, CLUSTER, GROUP, CUES, POINT, POSITIONS}


def size_of(n: int, width: int = 0) -> bytes:
    """A data size; all ones are kept for "unknown"."""
    width = width or next(w for w in range(1, 9) if n < (1 << 7 * w) - 1)
    return ((1 << 7 * width) | n).to_bytes(width, "big")


def element(kind: int, *body: bytes) -> bytes:
    body = b"".join(body)
    return kind.to_bytes((kind.bit_length() + 7) // 8, "big") + size_of(len(body)) + body


def number(kind: int, n: int) -> bytes:
    return element(kind, n.to_bytes(max(1, (n.bit_length() + 7) // 8), "big"))


def lace(frames: list[bytes], how: str) -> bytes:
    """The block content after its flags."""
    if how == "none":
        return frames[0]
    sizes, out = [len(f) for f in frames], bytes([len(frames) - 1])
    if how == "xiph":
        out += b"".join(b"\xff" * (n // 255) + bytes([n % 255]) for n in sizes[:-1])
    elif how == "ebml":
        out += size_of(sizes[0]) if len(sizes) > 1 else b""
        for a, b in zip(sizes, sizes[1:-1], strict=False):
            w = next(w for w in range(1, 9) if abs(b - a) < (1 << (7 * w - 1)) - 1)
            out += size_of(b - a + (1 << (7 * w - 1)) - 1, w)
    return out + b"".join(frames)


_LACING = {"none": 0, "xiph": 2, "fixed": 4, "ebml": 6}


def write(payload: bytes, frame: int = FRAME, per_block: int = 8, blocks: int = 8, lacing: str = "fixed", rate: int = RATE) -> bytes:
    """A file of one 8-bit mono PCM track whose frames, in order, are the payload."""
    ms = lambda k: k * frame * 1000 // rate
    n = -(-len(payload) // frame)
    head = element(EBML, number(VERSION, 1), number(READ_VERSION, 1), number(MAX_ID, 4), number(MAX_SIZE, 8), element(DOC_TYPE, b"matroska"), number(DOC_VERSION, 4), number(DOC_READ, 2))
    body = [element(INFO, number(SCALE, 1_000_000), element(DURATION, struct.pack(">d", ms(n))), element(MUXER, b"slicelink"), element(WRITER, b"slicelink"))]
    audio = element(AUDIO, element(FREQUENCY, struct.pack(">d", rate)), number(CHANNELS, 1), number(DEPTH, 8))
    body.append(element(TRACKS, element(ENTRY, number(NUMBER, 1), number(UID, 1), number(TYPE, 2), number(LACED, 1), element(CODEC, b"A_PCM/INT/LIT"), number(DEFAULT_DURATION, frame * 1_000_000_000 // rate), audio)))
    at, cues = sum(map(len, body)), []
    per_block = 1 if lacing == "none" else per_block
    for c in range(0, n, per_block * blocks):
        parts = [number(TIMECODE, ms(c))]
        for b in range(c, min(n, c + per_block * blocks), per_block):
            own = payload[b * frame : min(n, b + per_block, c + per_block * blocks) * frame]
            inner = bytes([len(own) // frame - 1]) + own if lacing == "fixed" and len(own) % frame == 0 else lace([own[i : i + frame] for i in range(0, len(own), frame)], lacing)
            parts.append(element(SIMPLE, b"\x81" + struct.pack(">h", ms(b) - ms(c)) + bytes([0x80 | _LACING[lacing]]), inner))
        cues.append(element(POINT, number(CUE_TIME, ms(c)), element(POSITIONS, number(CUE_TRACK, 1), number(CUE_CLUSTER, at))))
        body.append(element(CLUSTER, *parts))
        at += len(body[-1])
    return head + element(SEGMENT, *body, element(CUES, *cues))


def _vint(data, at: int, keep: bool) -> tuple[int | None, int]:
    """An element's id (keep the marker) or data size (None: unknown), and where it ends."""
    first = data[at]
    width = 9 - first.bit_length()
    if width > 8 or at + width > len(data):
        raise IndexError
    n = int.from_bytes(data[at : at + width], "big")
    if not keep:
        n &= (1 << 7 * width) - 1
        if n == (1 << 7 * width) - 1:
            n = None
    return n, at + width


def _frames(data, at: int, end: int, how: int) -> list[tuple[int, int]]:
    """Byte ranges of a block's frames; at: after the flags."""
    if not how:
        return [(at, end)]
    n = data[at] + 1
    at += 1
    if how == 4:
        if (end - at) % n:
            raise IndexError
        step = (end - at) // n
        return [(at + k * step, at + (k + 1) * step) for k in range(n)]
    sizes: list[int] = []
    for k in range(n - 1):
        if how == 2:
            size = 0
            while True:
                size, at = size + data[at], at + 1
                if data[at - 1] < 255:
                    break
        else:
            begin = at
            size, at = _vint(data, at, False)
            if k:
                size += sizes[-1] - ((1 << (7 * (at - begin) - 1)) - 1)
        sizes.append(size)
    sizes.append(end - at - sum(sizes))
    if min(sizes) < 0:
        raise IndexError
    out = []
    for size in sizes:
        out.append((at, at + size))
        at += size
    return out


def parse(data: bytes) -> dict:
    """tracks: {number: {type, codec, rate, depth, default_ns}}, packets: [(track, ns, begin, end, key)], cues: [(ns, track, cluster's byte)]."""
    tracks, packets, cues = {}, [], []
    state = {"scale": 1_000_000, "cluster": 0, "segment": 0, "entry": {}, "cue": 0, "point": {}}
    uint = lambda a, b: int.from_bytes(data[a:b], "big")
    real = lambda a, b: struct.unpack(">d" if b - a == 8 else ">f", data[a:b])[0] if b - a in (4, 8) else 0.0

    def block(at, end, key):
        track, at = _vint(data, at, False)
        offset, flags = struct.unpack(">hB", data[at : at + 3])
        ns = (state["cluster"] + offset) * state["scale"]
        step = tracks.get(track, {}).get("default_ns", 0)
        for k, (a, b) in enumerate(_frames(data, at + 3, end, flags & 6)):
            packets.append((track, ns + k * step, a, b, key if key is not None else bool(flags & 0x80)))

    stack, at, open_cluster = [len(data)], 0, False
    try:
        while True:
            while len(stack) > 1 and at >= stack[-1]:
                stack.pop()
            if at >= stack[-1]:
                break
            kind, at = _vint(data, at, True)
            size, at = _vint(data, at, False)
            if open_cluster and kind in (CLUSTER, CUES, TRACKS, INFO):  # a cluster of unknown size ends where its next sibling begins
                stack.pop()
                open_cluster = False
            end = stack[-1] if size is None else at + size
            open_cluster |= kind == CLUSTER and size is None
            if kind in PARENTS:
                if kind == SEGMENT:
                    state["segment"] = at
                elif kind == ENTRY:
                    state["entry"] = {}
                if kind == GROUP:
                    at = _group(data, at, end, block)
                    continue
                stack.append(end)
                continue
            if end > len(data):
                break
            if kind == SCALE:
                state["scale"] = uint(at, end)
            elif kind == NUMBER:
                tracks[uint(at, end)] = state["entry"]
            elif kind in (TYPE, DEPTH, CHANNELS, DEFAULT_DURATION):
                state["entry"][{TYPE: "type", DEPTH: "depth", CHANNELS: "channels", DEFAULT_DURATION: "default_ns"}[kind]] = uint(at, end)
            elif kind == CODEC:
                state["entry"]["codec"] = data[at:end].decode("ascii", "replace")
            elif kind == FREQUENCY:
                state["entry"]["rate"] = real(at, end)
            elif kind == TIMECODE:
                state["cluster"] = uint(at, end)
            elif kind == SIMPLE:
                block(at, end, None)
            elif kind == CUE_TIME:
                state["cue"] = uint(at, end) * state["scale"]
            elif kind == CUE_TRACK:
                state["point"] = uint(at, end)
            elif kind == CUE_CLUSTER:
                cues.append((state["cue"], state["point"], state["segment"] + uint(at, end)))
            at = end
    except (IndexError, struct.error):
        pass
    return {"tracks": tracks, "packets": packets, "cues": cues}


def _group(data, at: int, end: int, block) -> int:
    """A block group: a key frame unless it refers to another."""
    own, key = None, True
    while at < end:
        kind, at = _vint(data, at, True)
        size, at = _vint(data, at, False)
        if kind == BLOCK:
            own = (at, at + size)
        elif kind == REFERENCE:
            key = False
        at += size
    if own:
        block(*own, key)
    return end


PACKETS = "doc_id long, track int, packet int, timestamp_ns long, byte_start long, byte_end long, is_key boolean"


def packet_table(media, id_col: str = "doc_id", media_col: str = "media"):
    """One row per packet of each file in a binary column."""

    def run(batches):
        for batch in batches:
            for doc, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                rows = [(doc, t, k, ns, a, b, key) for k, (t, ns, a, b, key) in enumerate(parse(data or b"")["packets"])]
                if rows:
                    types = [pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.bool_()]
                    yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), types, strict=True)], names=[x.split()[0] for x in PACKETS.split(", ")])

    ready(media.sparkSession)
    return media.select(media[id_col].cast("long").alias("i"), media[media_col].alias("m")).mapInArrow(run, PACKETS)


def padded(data: bytes, unit: int = FRAME) -> bytes:
    return data + b"\xff" * (-len(data) % unit or (0 if data else unit))


def features(payload: bytes, packets: list) -> str:
    """Packets, milliseconds, mean and deviation of the samples, share of sign changes, loudest and softest frame."""
    x = np.frombuffer(payload, np.uint8).astype(np.int32) - 128
    power = (x * x).reshape(-1, FRAME).sum(1)
    turns = int(np.count_nonzero((x[1:] >= 0) != (x[:-1] >= 0)))
    mean, square = int(x.sum()) / len(x), int(power.sum()) / len(x)
    return f"packets={len(packets)};ms={packets[-1][1] // 1_000_000 + FRAME * 1000 // RATE};mean={mean:.4f};dev={max(0.0, square - mean * mean) ** 0.5:.4f};turns={turns / len(x):.4f};peak={int(power.max())};floor={int(power.min())}"


DIGEST = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_packets int, n_cues int"


def store(docs, id_col: str = "doc_id", text_col: str = "text"):
    """Each text as media bytes: columns doc_id, media."""

    def run(batches):
        for part in slices(batches, "t"):
            data, off = raw(part.column(1))
            media = [write(padded(data[a:b].tobytes())) for a, b in zip(off[:-1], off[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(media, pa.binary())], names=["doc_id", "media"])

    ready(docs.sparkSession)
    return docs.select(docs[id_col].cast("long").alias("i"), docs[text_col].alias("t")).mapInArrow(run, "doc_id long, media binary")


def digest(docs, id_col: str = "doc_id", text_col: str = "text"):
    """Store each text, read the stored bytes back through the parser, and describe both (DIGEST)."""

    def run(batches):
        for part in slices(batches, "t"):
            data, off = raw(part.column(1))
            rows = []
            for doc, a, b in zip(part.column(0).to_pylist(), off[:-1].tolist(), off[1:].tolist(), strict=True):
                media = write(padded(data[a:b].tobytes()))
                seen = parse(media)
                view = memoryview(media)
                payload = b"".join([view[x:y] for _, _, x, y, _ in seen["packets"]])
                rows.append((doc, b - a, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(media), hashlib.sha256(media).hexdigest(), features(payload, seen["packets"]), len(seen["packets"]), len(seen["cues"])))
            kinds = {"long": pa.int64(), "string": pa.string(), "int": pa.int32()}
            fields = [x.split() for x in DIGEST.split(", ")]
            yield pa.RecordBatch.from_arrays([pa.array(x, kinds[k]) for x, (_, k) in zip(zip(*rows, strict=True), fields, strict=True)], names=[n for n, _ in fields])

    ready(docs.sparkSession)
    return docs.select(docs[id_col].cast("long").alias("i"), docs[text_col].alias("t")).mapInArrow(run, DIGEST)


def op8_matroska(spark, sf_dir):
    return digest(table(spark, sf_dir, "documents"))
