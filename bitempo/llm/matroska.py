"""Media columns in Matroska: EBML elements, clusters, lacing and cues, read into packet tables.

``write_audio`` stores bytes as 8-bit PCM samples of one track; ``read_file`` parses any Matroska file held in a binary column:
variable-length element ids and sizes (unknown sizes too), simple blocks and block groups, and the four kinds of lacing.
A packet row has its track, timestamp in milliseconds, byte range in the file and whether it is a key frame.

Cases: a null or empty text is a payload of 64 zero bytes; equal payloads give equal files; broken files give the packets that
are whole and no error; a null file has no packets; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

# Element ids of the Matroska format (fixed values)
EBML, SEGMENT, INFO, TRACKS, CLUSTER, CUES = 0x1A45DFA3, 0x18538067, 0x1549A966, 0x1654AE6B, 0x1F43B675, 0x1C53BB6B
EBML_VERSION, EBML_READ_VERSION, MAX_ID, MAX_SIZE = 0x4286, 0x42F7, 0x42F2, 0x42F3
DOC_TYPE, DOC_TYPE_VERSION, DOC_TYPE_READ_VERSION = 0x4282, 0x4287, 0x4285
TIMESTAMP_SCALE, MUXING_APP, WRITING_APP = 0x2AD7B1, 0x4D80, 0x5741
TRACK_ENTRY, TRACK_NUMBER, TRACK_UID, TRACK_TYPE, CODEC_ID, FLAG_LACING = 0xAE, 0xD7, 0x73C5, 0x83, 0x86, 0x9C
AUDIO, SAMPLING, CHANNELS, BIT_DEPTH = 0xE1, 0xB5, 0x9F, 0x6264
TIMESTAMP, SIMPLE_BLOCK, BLOCK_GROUP, BLOCK = 0xE7, 0xA3, 0xA0, 0xA1
CUE_POINT, CUE_TIME, CUE_POSITIONS, CUE_TRACK, CUE_CLUSTER = 0xBB, 0xB3, 0xB7, 0xF7, 0xF1
PARENTS = {SEGMENT, INFO, TRACKS, CLUSTER, CUES, TRACK_ENTRY, AUDIO, BLOCK_GROUP, CUE_POINT, CUE_POSITIONS}
#: Elements that end a cluster or segment of unknown size.
TOP = {SEGMENT, INFO, TRACKS, CLUSTER, CUES}

RATE, FRAME, LACED, BLOCKS = 8000, 1024, 8, 4  # samples a second, bytes a frame, frames a block, blocks a cluster


def size_bytes(n: int) -> bytes:
    """A size as a variable-length integer; all ones would mean an unknown size."""
    width = 1
    while n >= (1 << 7 * width) - 1:
        width += 1
    return (n | 1 << 7 * width).to_bytes(width, "big")


def element(ident: int, data: bytes) -> bytes:
    return ident.to_bytes((ident.bit_length() + 7) // 8, "big") + size_bytes(len(data)) + data


def number(ident: int, n: int) -> bytes:
    return element(ident, n.to_bytes(max(1, (n.bit_length() + 7) // 8), "big"))


_HEAD = element(
    EBML,
    number(EBML_VERSION, 1) + number(EBML_READ_VERSION, 1) + number(MAX_ID, 4) + number(MAX_SIZE, 8)
    + element(DOC_TYPE, b"matroska") + number(DOC_TYPE_VERSION, 4) + number(DOC_TYPE_READ_VERSION, 2),
)
_SETUP = element(INFO, number(TIMESTAMP_SCALE, 1_000_000) + element(MUXING_APP, b"bitempo") + element(WRITING_APP, b"bitempo")) + element(
    TRACKS,
    element(
        TRACK_ENTRY,
        number(TRACK_NUMBER, 1) + number(TRACK_UID, 1) + number(TRACK_TYPE, 2) + number(FLAG_LACING, 1) + element(CODEC_ID, b"A_PCM/INT/LIT")
        + element(AUDIO, element(SAMPLING, struct.pack(">d", float(RATE))) + number(CHANNELS, 1) + number(BIT_DEPTH, 8)),
    ),
)


def lace(frames: list[bytes]) -> tuple[int, bytes]:
    """Lacing flag bits and the block's data: none for one frame, fixed for equal ones, else EBML lacing."""
    if len(frames) == 1:
        return 0, frames[0]
    if len({len(f) for f in frames}) == 1:
        return 0x04, bytes([len(frames) - 1]) + b"".join(frames)
    head = [bytes([len(frames) - 1]), size_bytes(len(frames[0]))]
    for before, now in zip(frames, frames[1:-1]):
        step, width = len(now) - len(before), 1
        while not -(1 << 7 * width - 1) < step < (1 << 7 * width - 1):
            width += 1
        head.append((step + (1 << 7 * width - 1) - 1 | 1 << 7 * width).to_bytes(width, "big"))
    return 0x06, b"".join(head + frames)


def write_audio(payload: bytes, frame: int = FRAME, laced: int = LACED, blocks: int = BLOCKS) -> bytes:
    """A Matroska file with the payload as 8-bit samples of track 1."""
    frames = [payload[i : i + frame] for i in range(0, len(payload), frame)]
    clusters, cues, at = [], [], len(_SETUP)
    for first in range(0, len(frames), laced * blocks):
        start = first * frame * 1000 // RATE
        body = [number(TIMESTAMP, start)]
        for b in range(first, min(first + laced * blocks, len(frames)), laced):
            flag, data = lace(frames[b : b + laced])
            body.append(element(SIMPLE_BLOCK, b"\x81" + struct.pack(">hB", b * frame * 1000 // RATE - start, 0x80 | flag) + data))
        cluster = element(CLUSTER, b"".join(body))
        cues.append(element(CUE_POINT, number(CUE_TIME, start) + element(CUE_POSITIONS, number(CUE_TRACK, 1) + number(CUE_CLUSTER, at))))
        clusters.append(cluster)
        at += len(cluster)
    return _HEAD + element(SEGMENT, b"".join([_SETUP, *clusters, element(CUES, b"".join(cues))]))


@dataclass
class Media:
    """What a file holds: tracks (number → codec, rate, bits), packets (track, ms, offset, size, key, cluster offset), cues (ms, track, cluster)."""

    tracks: dict[int, dict] = field(default_factory=dict)
    packets: list[tuple[int, float, int, int, bool, int]] = field(default_factory=list)
    cues: list[tuple[int, int, int]] = field(default_factory=list)
    scale: int = 1_000_000
    segment: int = 0

    def payload(self, data: bytes, track: int = 1) -> bytes:
        return b"".join([data[p[2] : p[2] + p[3]] for p in self.packets if p[0] == track])


def _vint(data: bytes, at: int, keep_marker: bool = False) -> tuple[int | None, int]:
    """A variable-length integer at ``at`` and the place after it; None if all its bits are ones (an unknown size)."""
    first = data[at]
    width = 9 - first.bit_length()
    if width > 8 or at + width > len(data):
        raise IndexError(at)
    value = int.from_bytes(data[at : at + width], "big")
    if keep_marker:
        return value, at + width
    value &= (1 << 7 * width) - 1
    return (None if value == (1 << 7 * width) - 1 else value), at + width


def _frames(data: bytes, at: int, end: int, lacing: int) -> list[tuple[int, int]]:
    """Byte ranges of a block's frames."""
    if lacing == 0:
        return [(at, end - at)]
    n, at = data[at] + 1, at + 1
    if lacing == 2:  # fixed
        each = (end - at) // n
        return [(at + i * each, each) for i in range(n)]
    sizes: list[int] = []
    if lacing == 1:  # sizes as runs of 255
        for _ in range(n - 1):
            total = 0
            while data[at] == 255:
                total, at = total + 255, at + 1
            sizes.append(total + data[at])
            at += 1
    else:  # first size, then signed differences
        for i in range(n - 1):
            start = at
            value, at = _vint(data, at)
            width = at - start
            value = (1 << 7 * width) - 1 if value is None else value
            sizes.append(value if i == 0 else sizes[-1] + value - ((1 << 7 * width - 1) - 1))
    sizes.append(end - at - sum(sizes))
    out = []
    for n in sizes:
        if n < 0 or at + n > end:
            raise IndexError(at)
        out.append((at, n))
        at += n
    return out


def read_file(data: bytes | None) -> Media:
    media = Media()
    if data:
        try:
            _read(data, 0, len(data), media, {})
        except (IndexError, struct.error):
            pass  # the rest of the file is broken; what was whole stays
    return media


def _read(data: bytes, at: int, end: int, media: Media, inside: dict, unknown: bool = False) -> int:
    while at < end:
        begun = at
        ident, at = _vint(data, at, keep_marker=True)
        if unknown and ident in TOP and inside.get("kind") == CLUSTER:
            return begun
        size, at = _vint(data, at)
        stop = end if size is None else at + size
        if stop > end:
            if ident not in PARENTS:
                raise IndexError(at)
            stop = end
        body = lambda: int.from_bytes(data[at:stop], "big")  # noqa: B023, E731
        if ident in PARENTS:
            if ident == SEGMENT:
                media.segment = at
            own = {"kind": ident, "at": begun} if ident in (CLUSTER, TRACK_ENTRY, CUE_POINT) else {**inside, "kind": ident}
            own = inside if ident in (AUDIO, CUE_POSITIONS) else own
            stop = _read(data, at, stop, media, own, size is None)
            if ident == TRACK_ENTRY:
                media.tracks[own.get("number", 0)] = {k: v for k, v in own.items() if k in ("codec", "rate", "channels", "bits", "type")}
            elif ident == CUE_POINT and "cluster" in own:
                media.cues.append((own.get("time", 0), own.get("track", 0), own["cluster"]))
        elif ident in (SIMPLE_BLOCK, BLOCK):
            track, place = _vint(data, at)
            offset, flags = struct.unpack_from(">hB", data, place)
            frames = _frames(data, place + 3, stop, flags >> 1 & 3)
            known = media.tracks.get(track, {})
            per_byte = 1000 / (known["rate"] * known.get("channels", 1) * max(1, known.get("bits", 8) // 8)) if known.get("rate") and known.get("codec", "").startswith("A_PCM") else 0.0
            when = (inside.get("time", 0) + offset) * media.scale / 1e6
            for frame, n in frames:
                media.packets.append((track, when, frame, n, bool(flags & 0x80) or ident == BLOCK, inside.get("at", 0)))
                when += n * per_byte
        elif ident in (TIMESTAMP, CUE_TIME):
            inside["time"] = body()
        elif ident == TIMESTAMP_SCALE:
            media.scale = body()
        elif ident == SAMPLING:
            inside["rate"] = struct.unpack(">d" if stop - at == 8 else ">f", data[at:stop])[0]
        elif ident == CODEC_ID:
            inside["codec"] = data[at:stop].decode("ascii", "replace")
        elif ident in (TRACK_NUMBER, TRACK_TYPE, CHANNELS, BIT_DEPTH, CUE_TRACK, CUE_CLUSTER):
            key = {TRACK_NUMBER: "number", TRACK_TYPE: "type", CHANNELS: "channels", BIT_DEPTH: "bits", CUE_TRACK: "track", CUE_CLUSTER: "cluster"}[ident]
            inside[key] = body()
        at = stop
    return at


def padded(text: str | None) -> tuple[bytes, int]:
    """UTF-8 bytes with zeros up to a positive multiple of 64, and the number before them."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    return raw + bytes(-len(raw) % 64 if raw else 64), len(raw)


def sample_features(payload: bytes) -> str:
    """Count, mean, power, extremes, crossings of the middle value and loudest 64-sample stretch of 8-bit samples."""
    x = np.frombuffer(payload, np.uint8).astype(np.int64)
    power = (x - 128) ** 2
    side = x >= 128
    loudest = int(power[: len(x) // 64 * 64].reshape(-1, 64).sum(axis=1).argmax()) if len(x) >= 64 else 0
    return f"n={len(x)};sum={int(x.sum())};power={int(power.sum())};min={int(x.min())};max={int(x.max())};crossings={int((side[1:] != side[:-1]).sum())};loudest={loudest}"


def audio(text: Column) -> Column:
    """Binary column of Matroska files with the texts' bytes as samples."""

    @F.pandas_udf("binary")
    def of(texts: pd.Series) -> pd.Series:
        return pd.Series([write_audio(padded(t)[0]) for t in texts])

    return of(text)


def packet_table(media: Column) -> Column:
    """Array of packets of a binary column; explode it for one row a packet."""

    @F.pandas_udf("array<struct<track:int,ms:double,start:long,size:long,key:boolean,cluster:long>>")
    def of(files: pd.Series) -> pd.Series:
        names = ("track", "ms", "start", "size", "key", "cluster")
        return pd.Series([[dict(zip(names, p)) for p in read_file(f).packets] for f in files])

    return of(media)


_DIGEST = "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, packets int, feature string"


def read_back(media: Column) -> Column:
    """Struct of digests and features of the samples that a binary column of files holds."""

    @F.pandas_udf(_DIGEST)
    def of(files: pd.Series) -> pd.DataFrame:
        rows = []
        for data in files:
            data = bytes(data)
            found = read_file(data)
            payload = found.payload(data)
            rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(data), hashlib.sha256(data).hexdigest(), len(found.packets), sample_features(payload)))
        return pd.DataFrame(rows, columns=[c.split()[0] for c in _DIGEST.split(", ")])

    return of(media)
