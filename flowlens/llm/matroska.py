"""Media columns in Matroska: write losslessly, parse EBML, list packets with timestamps, tracks and byte ranges."""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import slices, table

# Fixed values of the container format: element ids.
EBML, EBML_VERSION, EBML_READ_VERSION, MAX_ID, MAX_SIZE, DOCTYPE, DOCTYPE_VERSION, DOCTYPE_READ = 0x1A45DFA3, 0x4286, 0x42F7, 0x42F2, 0x42F3, 0x4282, 0x4287, 0x4285
SEGMENT, INFO, TIMESTAMP_SCALE, DURATION, MUXING_APP, WRITING_APP = 0x18538067, 0x1549A966, 0x2AD7B1, 0x4489, 0x4D80, 0x5741
TRACKS, TRACK_ENTRY, TRACK_NUMBER, TRACK_UID, TRACK_TYPE, CODEC, LACING, DEFAULT_DURATION = 0x1654AE6B, 0xAE, 0xD7, 0x73C5, 0x83, 0x86, 0x9C, 0x23E383
AUDIO, SAMPLING, CHANNELS, BIT_DEPTH = 0xE1, 0xB5, 0x9F, 0x6264
CLUSTER, CLUSTER_TIME, SIMPLE_BLOCK, BLOCK_GROUP, BLOCK, BLOCK_DURATION = 0x1F43B675, 0xE7, 0xA3, 0xA0, 0xA1, 0x9B
CUES, CUE_POINT, CUE_TIME, CUE_POSITIONS, CUE_TRACK, CUE_CLUSTER = 0x1C53BB6B, 0xBB, 0xB3, 0xB7, 0xF7, 0xF1
MASTERS = frozenset({EBML, SEGMENT, INFO, TRACKS, TRACK_ENTRY, AUDIO, CLUSTER, BLOCK_GROUP, CUES, CUE_POINT, CUE_POSITIONS})
#: Elements that end a cluster or segment of unknown size.
TOP_LEVEL = frozenset({CLUSTER, CUES, TRACKS, INFO, SEGMENT, EBML})

#: A packet holds 576 8-bit samples at 8 kHz, so it lasts 72 ms; packets are laced 8 to a block, blocks 4 to a cluster.
SAMPLES, RATE, PER_BLOCK, PER_CLUSTER = 576, 8000, 8, 4
PACKET_MS = 1000 * SAMPLES // RATE
NONE, XIPH, FIXED, EBML_LACE = 0, 1, 2, 3


def vint(value: int, width: int = 0) -> bytes:
    """Variable-length size: a length marker bit, then 7 value bits a byte; the all-ones pattern is kept for unknown sizes."""
    width = width or next(n for n in range(1, 9) if value < (1 << 7 * n) - 1)
    return (value | 1 << 7 * width).to_bytes(width, "big")


def element(ident: int, body: bytes) -> bytes:
    return ident.to_bytes((ident.bit_length() + 7) // 8, "big") + vint(len(body)) + body


def uint(ident: int, value: int) -> bytes:
    return element(ident, value.to_bytes(max(1, (value.bit_length() + 7) // 8), "big"))


def lace(frames: list[bytes], mode: int) -> bytes:
    """Body of a block after its header: frame sizes in the chosen lacing, then the frames."""
    sizes = [len(f) for f in frames]
    head = b"" if mode == NONE else bytes([len(frames) - 1])
    if mode == XIPH:
        head += b"".join(b"\xff" * (n // 255) + bytes([n % 255]) for n in sizes[:-1])
    elif mode == EBML_LACE:
        head += vint(sizes[0])
        for before, n in zip(sizes[:-1], sizes[1:-1]):
            width = next(w for w in range(1, 9) if abs(n - before) < (1 << 7 * w - 1) - 1)
            head += vint(n - before + (1 << 7 * width - 1) - 1, width)
    elif mode == FIXED and len(set(sizes)) > 1:
        raise ValueError("fixed lacing needs frames of one size")
    return head + b"".join(frames)


def mux(payload: bytes, samples: int = SAMPLES) -> bytes:
    """A Matroska file with one 8-bit PCM track; the lacing cycles over Xiph, fixed and EBML, a lone frame has none."""
    frames = [payload[i : i + samples] for i in range(0, len(payload), samples)]
    ms = 1000 * samples // RATE
    head = element(EBML, uint(EBML_VERSION, 1) + uint(EBML_READ_VERSION, 1) + uint(MAX_ID, 4) + uint(MAX_SIZE, 8) + element(DOCTYPE, b"matroska") + uint(DOCTYPE_VERSION, 4) + uint(DOCTYPE_READ, 2))
    body = element(INFO, uint(TIMESTAMP_SCALE, 1_000_000) + element(DURATION, struct.pack(">d", float(len(frames) * ms))) + element(MUXING_APP, b"flowlens") + element(WRITING_APP, b"flowlens"))
    audio = element(AUDIO, element(SAMPLING, struct.pack(">d", float(RATE))) + uint(CHANNELS, 1) + uint(BIT_DEPTH, 8))
    body += element(TRACKS, element(TRACK_ENTRY, uint(TRACK_NUMBER, 1) + uint(TRACK_UID, 1) + uint(TRACK_TYPE, 2) + uint(LACING, 1) + element(CODEC, b"A_PCM/INT/LIT") + uint(DEFAULT_DURATION, ms * 1_000_000) + audio))
    cues, parts, at = [], [body], len(body)
    for c in range(0, len(frames), PER_BLOCK * PER_CLUSTER):
        start, blocks = c * ms, b""
        for b in range(c, min(len(frames), c + PER_BLOCK * PER_CLUSTER), PER_BLOCK):
            group = frames[b : b + PER_BLOCK]
            mode = NONE if len(group) == 1 else (XIPH, FIXED, EBML_LACE)[b // PER_BLOCK % 3]
            blocks += element(SIMPLE_BLOCK, vint(1) + struct.pack(">hB", b * ms - start, 0x80 | mode << 1) + lace(group, mode))
        cues.append(element(CUE_POINT, uint(CUE_TIME, start) + element(CUE_POSITIONS, uint(CUE_TRACK, 1) + uint(CUE_CLUSTER, at))))
        parts.append(element(CLUSTER, uint(CLUSTER_TIME, start) + blocks))
        at += len(parts[-1])
    parts.append(element(CUES, b"".join(cues)))
    return head + element(SEGMENT, b"".join(parts))


def read_vint(data: bytes, at: int, keep_marker: bool = False) -> tuple[int, int]:
    """(value, next position); a size of all ones is -1 (unknown)."""
    first = data[at]
    width = 9 - first.bit_length()
    if width > 8 or at + width > len(data):
        raise ValueError(f"bad variable-length integer at {at}")
    raw = int.from_bytes(data[at : at + width], "big")
    if keep_marker:
        return raw, at + width
    value = raw & (1 << 7 * width) - 1
    return (-1 if value == (1 << 7 * width) - 1 else value), at + width


def elements(data: bytes, at: int, end: int, depth: int = 0, parent: int = 0) -> Iterator[tuple[int, int, int, int, int]]:
    """(depth, id, start, body start, body end) in file order; masters come before their children. Unknown sizes end at the next sibling."""
    while at < end:
        start = at
        ident, at = read_vint(data, at, keep_marker=True)
        if parent == CLUSTER and ident in TOP_LEVEL:
            return
        size, at = read_vint(data, at)
        stop = end if size < 0 else at + size
        if stop > end:
            raise ValueError(f"element {ident:#x} at {start} runs past its parent")
        yield depth, ident, start, at, stop
        if ident in MASTERS:
            last = at
            for child in elements(data, at, stop, depth + 1, ident):
                if child[0] == depth + 1:
                    last = child[4]
                yield child
            if size < 0:
                stop = last
        at = stop


def unlace(data: bytes, at: int, end: int) -> tuple[int, int, int, list[tuple[int, int]]]:
    """(track, relative time, lacing, [(start, length)]) of a block's body."""
    track, at = read_vint(data, at)
    when, flags = struct.unpack_from(">hB", data, at)
    at += 3
    mode = flags >> 1 & 3
    if mode == NONE:
        return track, when, mode, [(at, end - at)]
    count, at = data[at] + 1, at + 1
    if mode == FIXED:
        if (end - at) % count:
            raise ValueError("fixed lacing does not divide its block")
        sizes = [(end - at) // count] * count
    else:
        sizes = []
        for i in range(count - 1):
            if mode == XIPH:
                n = 0
                while data[at] == 255:
                    n, at = n + 255, at + 1
                n, at = n + data[at], at + 1
            elif i == 0:
                n, at = read_vint(data, at)
            else:
                width = 9 - data[at].bit_length()
                step, at = read_vint(data, at)
                n = sizes[-1] + step - ((1 << 7 * width - 1) - 1)
            sizes.append(n)
        sizes.append(end - at - sum(sizes))
    spans = []
    for n in sizes:
        if n < 0 or at + n > end:
            raise ValueError("laced frames run past their block")
        spans.append((at, n))
        at += n
    return track, when, mode, spans


def demux(data: bytes) -> dict:
    """Tracks, cues and packets of a file. A packet: (track, timestamp ms, cluster, lacing, byte start, byte length)."""
    tracks, cues, packets = {}, [], []
    cluster, now, scale, segment, track = -1, 0, 1_000_000, 0, {}
    number = lambda a, b: int.from_bytes(data[a:b], "big")
    for _, ident, _, a, b in elements(data, 0, len(data)):
        if ident == SEGMENT:
            segment = a
        elif ident == TIMESTAMP_SCALE:
            scale = number(a, b)
        elif ident == TRACK_ENTRY:
            track = {}
        elif ident == TRACK_NUMBER:
            tracks[number(a, b)] = track
        elif ident == CODEC:
            track["codec"] = data[a:b].decode()
        elif ident == DEFAULT_DURATION:
            track["packet_ms"] = number(a, b) / 1e6
        elif ident == CLUSTER:
            cluster, now = cluster + 1, 0
        elif ident == CLUSTER_TIME:
            now = number(a, b)
        elif ident in (SIMPLE_BLOCK, BLOCK):
            n, when, mode, spans = unlace(data, a, b)
            every = tracks.get(n, {}).get("packet_ms", 0)
            packets += [(n, int((now + when) * scale / 1e6 + i * every), cluster, mode, s, k) for i, (s, k) in enumerate(spans)]
        elif ident == CUE_TIME:
            cues.append([number(a, b), 0, 0])
        elif ident == CUE_TRACK:
            cues[-1][1] = number(a, b)
        elif ident == CUE_CLUSTER:
            cues[-1][2] = segment + number(a, b)
    return {"tracks": tracks, "cues": [tuple(c) for c in cues], "packets": packets}


def payload_of(data: bytes) -> bytes:
    return b"".join(data[s : s + n] for *_, s, n in demux(data)["packets"])


def padded(text: str | None, unit: int = SAMPLES) -> tuple[bytes, int]:
    raw = (text or "").encode("utf-8", "surrogatepass")
    return raw + b"\xff" * ((unit - len(raw) % unit) % unit or (0 if raw else unit)), len(raw)


MEDIA_SCHEMA = "doc_id long, n_bytes long, media binary"
PACKET_SCHEMA = "doc_id long, track int, packet int, timestamp_ms long, cluster int, lacing int, byte_start long, byte_length long, error string"
DIGEST_SCHEMA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, error string"


def media_column(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, media: every whole text as a Matroska file. Null and empty texts hold one packet of padding. Row by row:
    repeated rows repeat their result, null ids stay null, other columns are ignored, an empty table gives an empty result."""

    def run(batches):
        for b in slices(batches):
            made = [padded(t) for t in b.column(1).to_pylist()]
            yield pa.record_batch([b.column(0), pa.array([n for _, n in made], pa.int64()), pa.array([mux(p) for p, _ in made], pa.binary())], ["doc_id", "n_bytes", "media"])

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, MEDIA_SCHEMA)


def packet_table(media: DataFrame, id_col: str = "doc_id", media_col: str = "media") -> DataFrame:
    """One row per packet of every file; a damaged file gives one row with its error, a null file none."""
    names = ["doc_id", "track", "packet", "timestamp_ms", "cluster", "lacing", "byte_start", "byte_length", "error"]
    kinds = [pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.string()]

    def run(batches):
        for b in slices(batches):
            for i, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                if data is None:
                    continue
                try:
                    rows = [(i, t, k, ms, c, mode, s, n, None) for k, (t, ms, c, mode, s, n) in enumerate(demux(data)["packets"])]
                except (ValueError, IndexError, struct.error) as e:
                    rows = [(i, None, None, None, None, None, None, None, str(e))]
                if rows:
                    yield pa.record_batch([pa.array(col, kind) for col, kind in zip(zip(*rows), kinds)], names)

    return media.select(media[id_col].cast("long").alias("doc_id"), media[media_col].alias("media")).mapInArrow(run, PACKET_SCHEMA)


def media_digest(media: DataFrame) -> DataFrame:
    """Digest of each stored file: what its packets hold when read back, and features of the packet table. A damaged file gives its
    error in place of what it cannot say, a null file nothing but its id and size; an empty table gives an empty result."""
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "error"]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string()]

    def one(i, n, data):
        if data is None:
            return (i, n, *[None] * 7)
        try:
            got = demux(data)
            packets = got["packets"]
            body = b"".join(data[s : s + k] for *_, s, k in packets)
            mean = sum(body) / max(1, len(body))
            feature = f"packets={len(packets)};clusters={1 + max((p[2] for p in packets), default=-1)};cues={len(got['cues'])};ms={packets[-1][1] if packets else 0};lacing={''.join(map(str, sorted({p[3] for p in packets})))};mean={mean:.6f}"
            return (i, n, len(body), hashlib.sha256(body).hexdigest(), zlib.crc32(body[-32:]), len(data), hashlib.sha256(data).hexdigest(), feature, None)
        except (ValueError, IndexError, struct.error) as e:
            return (i, n, None, None, None, len(data), hashlib.sha256(data).hexdigest(), None, str(e))

    def run(batches):
        for b in slices(batches):
            rows = [one(*r) for r in zip(*(c.to_pylist() for c in b.columns))]
            if rows:
                yield pa.record_batch([pa.array(col, kind) for col, kind in zip(zip(*rows), kinds)], names)

    return media.select("doc_id", "n_bytes", "media").mapInArrow(run, DIGEST_SCHEMA)


def op9_matroska(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_digest(media_column(table(spark, sf_dir, "documents")))
