"""Media columns in Matroska: bytes stored losslessly as 8-bit PCM in laced blocks, parsed back into packet tables.

The writer makes an EBML header and a segment of seek head, info, one audio track, clusters of simple blocks and cues.
The parser reads variable-length elements of known or unknown size, all four lacings, block groups and cues, and
yields packets (track, timestamp, offset, size), so a reader can fetch byte ranges alone.

A media column is written first (`store`), then parsed into packet lists (`indexed`, or exploded by `packets`), and a
payload is read back by the byte ranges of those lists alone (`ranges`).

Defined results: a null text is stored like the empty one (64 zero bytes); equal texts give equal bytes; repeated rows
repeat; an empty table gives no rows; a damaged file raises ValueError in `demux`, gives an `error` and no packets in
`indexed` and a row with that `error` in `packets`. A null media value has no packets.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probseq.llm.common import map_parts, settle, utf8

# Fixed values of the format (RFC 8794, RFC 9559): element ids.
EBML, SEGMENT, SEEK_HEAD, SEEK, SEEK_ID, SEEK_POSITION = 0x1A45DFA3, 0x18538067, 0x114D9B74, 0x4DBB, 0x53AB, 0x53AC
INFO, TIMESTAMP_SCALE, DURATION, MUXING_APP, WRITING_APP = 0x1549A966, 0x2AD7B1, 0x4489, 0x4D80, 0x5741
TRACKS, TRACK_ENTRY, TRACK_NUMBER, TRACK_UID, TRACK_TYPE, CODEC_ID, LACING = 0x1654AE6B, 0xAE, 0xD7, 0x73C5, 0x83, 0x86, 0x9C
AUDIO, SAMPLING, CHANNELS, BIT_DEPTH = 0xE1, 0xB5, 0x9F, 0x6264
CLUSTER, TIMESTAMP, SIMPLE_BLOCK, BLOCK_GROUP, BLOCK = 0x1F43B675, 0xE7, 0xA3, 0xA0, 0xA1
CUES, CUE_POINT, CUE_TIME, CUE_POSITIONS, CUE_TRACK, CUE_CLUSTER = 0x1C53BB6B, 0xBB, 0xB3, 0xB7, 0xF7, 0xF1
VOID, CRC32 = 0xEC, 0xBF

RATE = 8000  # samples a second
FRAME = 512  # samples of a frame: 64 ms
LACED = 8  # frames of a block
BLOCKS = 16  # blocks of a cluster
PAD = 64


def size_of(n: int, width: int = 0) -> bytes:
    """A variable-length size, in `width` bytes or the fewest."""
    width = width or next(w for w in range(1, 9) if n < (1 << (7 * w)) - 1)
    return (n | 1 << (7 * width)).to_bytes(width, "big")


def element(key: int, body: bytes) -> bytes:
    return key.to_bytes((key.bit_length() + 7) // 8, "big") + size_of(len(body)) + body


def number(key: int, n: int, width: int = 0) -> bytes:
    return element(key, n.to_bytes(width or max(1, (n.bit_length() + 7) // 8), "big"))


def lace(frames: list[bytes], kind: str) -> tuple[int, bytes]:
    """(flag bits, head and frames) of a block; kind: none, xiph, fixed, ebml."""
    body = b"".join(frames)
    if kind == "none":
        if len(frames) != 1:
            raise ValueError("one frame fills a block without lacing")
        return 0x00, body
    head = bytes([len(frames) - 1])
    if kind == "fixed":
        if len({len(f) for f in frames}) > 1:
            raise ValueError("fixed lacing needs equal frames")
        return 0x04, head + body
    sizes = [len(f) for f in frames[:-1]]
    if kind == "xiph":
        return 0x02, head + b"".join(b"\xff" * (n // 255) + bytes([n % 255]) for n in sizes) + body
    out, last = [size_of(sizes[0])] if sizes else [], sizes[0] if sizes else 0
    for n in sizes[1:]:
        d = n - last
        width = next(w for w in range(1, 9) if abs(d) < (1 << (7 * w - 1)) - 1)
        out.append(size_of(d + (1 << (7 * width - 1)) - 1, width))
        last = n
    return 0x06, head + b"".join(out) + body


_head = element(EBML, number(0x4286, 1) + number(0x42F7, 1) + number(0x42F2, 4) + number(0x42F3, 8) + element(0x4282, b"matroska") + number(0x4287, 4) + number(0x4285, 2))
_tracks = element(
    TRACKS,
    element(
        TRACK_ENTRY,
        number(TRACK_NUMBER, 1) + number(TRACK_UID, 1) + number(TRACK_TYPE, 2) + number(LACING, 1) + element(CODEC_ID, b"A_PCM/INT/LIT")
        + element(AUDIO, element(SAMPLING, struct.pack(">d", RATE)) + number(CHANNELS, 1) + number(BIT_DEPTH, 8)),
    ),
)


def padded(text: bytes) -> bytes:
    """Zero bytes up to a positive multiple of 64."""
    return text + bytes(max(PAD, -(-len(text) // PAD) * PAD) - len(text))


def mux(payload: bytes, lacing: str = "auto") -> bytes:
    """A Matroska file that holds `payload` as unsigned 8-bit samples."""
    frames = [payload[i : i + FRAME] for i in range(0, len(payload), FRAME)]
    step = FRAME * 1000 // RATE
    clusters, cues, at, per = [], [], 0, LACED * BLOCKS
    for c in range(0, len(frames), per):
        start = c * step
        blocks = []
        for b in range(c, min(c + per, len(frames)), LACED):
            own = frames[b : min(b + LACED, c + per)]
            kind = lacing if lacing != "auto" and len(own) > 1 else "none" if len(own) == 1 else "fixed" if len(own[-1]) == FRAME else "ebml"
            flag, body = lace(own, "ebml" if kind == "fixed" and len(own[-1]) != len(own[0]) else kind)
            blocks.append(element(SIMPLE_BLOCK, b"\x81" + struct.pack(">hB", b * step - start, 0x80 | flag) + body))
        cluster = element(CLUSTER, number(TIMESTAMP, start) + b"".join(blocks))
        cues.append((start, at))
        clusters.append(cluster)
        at += len(cluster)
    info = element(
        INFO,
        number(TIMESTAMP_SCALE, 1_000_000) + element(DURATION, struct.pack(">d", len(payload) * 1000 / RATE)) + element(MUXING_APP, b"probseq") + element(WRITING_APP, b"probseq"),
    )
    seeks = lambda places: element(SEEK_HEAD, b"".join(element(SEEK, number(SEEK_ID, k, 4) + number(SEEK_POSITION, p, 8)) for k, p in places))
    base = len(seeks([(INFO, 0), (TRACKS, 0), (CUES, 0)]))
    first = base + len(info) + len(_tracks)
    head = seeks([(INFO, base), (TRACKS, base + len(info)), (CUES, first + at)])
    table = element(CUES, b"".join(element(CUE_POINT, number(CUE_TIME, t) + element(CUE_POSITIONS, number(CUE_TRACK, 1) + number(CUE_CLUSTER, first + p))) for t, p in cues))
    return _head + element(SEGMENT, b"".join([head, info, _tracks, *clusters, table]))


@dataclass
class Packet:
    track: int
    timestamp: int
    offset: int
    size: int
    key: bool
    cluster: int  # place of its cluster within the segment


@dataclass
class Media:
    tracks: dict[int, dict] = field(default_factory=dict)
    packets: list[Packet] = field(default_factory=list)
    cues: list[tuple[int, int, int]] = field(default_factory=list)  # time, track, cluster place
    seeks: dict[int, int] = field(default_factory=dict)
    scale: int = 1_000_000
    duration: float = 0.0
    clusters: int = 0


def vint(data: bytes, at: int, keep_mark: bool) -> tuple[int, int]:
    """(value, next place); with the mark kept for ids; -1 for an unknown size."""
    if at >= len(data) or not data[at]:
        raise ValueError(f"no variable-length number at {at}")
    width = 9 - data[at].bit_length()
    if at + width > len(data):
        raise ValueError(f"cut short at {at}")
    n = int.from_bytes(data[at : at + width], "big")
    if keep_mark:
        return n, at + width
    n &= (1 << (7 * width)) - 1
    return (-1 if n == (1 << (7 * width)) - 1 else n), at + width


# What ends an element of unknown size: elements of its own level or above.
_ends = {SEGMENT: {EBML, SEGMENT}, CLUSTER: {EBML, SEGMENT, SEEK_HEAD, INFO, TRACKS, CLUSTER, CUES}}


def children(data: bytes, at: int, end: int, parent: int = 0):
    """(id, start of the element, start and end of its body) of each child in data[at:end]."""
    while at < end:
        start = at
        key, at = vint(data, at, True)
        if key in _ends.get(parent, ()):
            return
        n, at = vint(data, at, False)
        if n < 0:
            if key not in _ends:
                raise ValueError(f"unknown size of element {key:x}")
            stop = at
            for k, s, _, e in children(data, at, end, key):
                stop = e
        else:
            stop = at + n
        if stop > end:
            raise ValueError(f"element {key:x} at {start} is cut short")
        yield key, start, at, stop
        at = stop


def unlace(data: bytes, at: int, end: int, kind: int) -> list[tuple[int, int]]:
    """(offset, size) of the frames of a block; kind: the two lacing bits."""
    if not kind:
        return [(at, end - at)]
    count, at = data[at] + 1, at + 1
    sizes: list[int] = []
    if kind == 2:
        if (end - at) % count:
            raise ValueError("fixed lacing does not divide the block")
        sizes = [(end - at) // count] * count
    else:
        for i in range(count - 1):
            if kind == 1:
                n = 0
                while data[at] == 255:
                    n, at = n + 255, at + 1
                n, at = n + data[at], at + 1
            else:
                before = at
                n, at = vint(data, at, False)
                if i:
                    n += sizes[-1] - (1 << (7 * (at - before) - 1)) + 1
            sizes.append(n)
        sizes.append(end - at - sum(sizes))
        if min(sizes) < 0:
            raise ValueError("laced frames exceed the block")
    out = []
    for n in sizes:
        out.append((at, n))
        at += n
    return out


def demux(data: bytes) -> Media:
    """Parses a file into tracks, packets and cues; offsets are places in `data`."""
    m, uint = Media(), lambda a, b: int.from_bytes(data[a:b], "big")
    real = lambda a, b: struct.unpack(">d" if b - a == 8 else ">f", data[a:b])[0]

    def block(a: int, b: int, time: int, place: int, simple: bool) -> None:
        track, a = vint(data, a, False)
        relative, flags = struct.unpack(">hB", data[a : a + 3])
        for i, (o, n) in enumerate(unlace(data, a + 3, b, flags >> 1 & 3)):
            step = m.tracks.get(track, {}).get("rate", 0)
            after = int(sum(p.size for p in m.packets[len(m.packets) - i :]) * 1000 / step) if i and step else 0
            m.packets.append(Packet(track, time + relative + after, o, n, not simple or bool(flags & 0x80), place))

    for key, _, a, b in children(data, 0, len(data)):
        if key == EBML:
            if not any(k == 0x4282 and data[x:y] in (b"matroska", b"webm") for k, _, x, y in children(data, a, b)):
                raise ValueError("not a Matroska file")
        elif key == SEGMENT:
            base = a
            for k, start, x, y in children(data, a, b, SEGMENT):
                if k == INFO:
                    for k2, _, p, q in children(data, x, y):
                        if k2 == TIMESTAMP_SCALE:
                            m.scale = uint(p, q)
                        elif k2 == DURATION:
                            m.duration = real(p, q)
                elif k == SEEK_HEAD:
                    for _, _, p, q in children(data, x, y):
                        own = {k3: uint(r, s) for k3, _, r, s in children(data, p, q)}
                        m.seeks[own.get(SEEK_ID, 0)] = own.get(SEEK_POSITION, 0)
                elif k == TRACKS:
                    for k2, _, p, q in children(data, x, y):
                        if k2 == TRACK_ENTRY:
                            t: dict = {}
                            for k3, _, r, s in children(data, p, q):
                                if k3 == TRACK_NUMBER:
                                    t["number"] = uint(r, s)
                                elif k3 == CODEC_ID:
                                    t["codec"] = data[r:s].decode()
                                elif k3 == AUDIO:
                                    for k4, _, u, v in children(data, r, s):
                                        if k4 == SAMPLING:
                                            t["rate"] = real(u, v)
                                        elif k4 in (CHANNELS, BIT_DEPTH):
                                            t["channels" if k4 == CHANNELS else "bits"] = uint(u, v)
                            m.tracks[t.get("number", 0)] = t
                elif k == CLUSTER:
                    m.clusters, time = m.clusters + 1, 0
                    for k2, _, p, q in children(data, x, y, CLUSTER):
                        if k2 == TIMESTAMP:
                            time = uint(p, q)
                        elif k2 == SIMPLE_BLOCK:
                            block(p, q, time, start - base, True)
                        elif k2 == BLOCK_GROUP:
                            for k3, _, r, s in children(data, p, q):
                                if k3 == BLOCK:
                                    block(r, s, time, start - base, False)
                elif k == CUES:
                    for _, _, p, q in children(data, x, y):
                        when, where = 0, []
                        for k3, _, r, s in children(data, p, q):
                            if k3 == CUE_TIME:
                                when = uint(r, s)
                            elif k3 == CUE_POSITIONS:
                                own = {k4: uint(u, v) for k4, _, u, v in children(data, r, s)}
                                where.append((own.get(CUE_TRACK, 0), own.get(CUE_CLUSTER, 0)))
                        m.cues += [(when, t, c) for t, c in where]
    return m


def payload_of(data: bytes, media: Media, track: int = 1) -> bytes:
    return b"".join([data[p.offset : p.offset + p.size] for p in media.packets if p.track == track])


def feature_of(packets: int, clusters: int, cues: int, duration: float, payload: bytes) -> str:
    """Packets, clusters, cues, duration in ms, and mean, deviation and mean absolute step of the samples."""
    x = np.frombuffer(payload, np.uint8)
    counts = np.bincount(x, minlength=256)  # sums by value: exact, and no wider copy of a long payload
    value = np.arange(256)
    mean = float((counts * value).sum() / max(1, len(x)))
    sd = float(np.sqrt((counts * (value - mean) ** 2).sum() / max(1, len(x))))
    step = float((np.maximum(x[1:], x[:-1]) - np.minimum(x[1:], x[:-1])).mean()) if len(x) > 1 else 0.0
    return f"packets={packets};clusters={clusters};cues={cues};ms={duration:.0f};mean={mean:.4f};sd={sd:.4f};step={step:.4f}"


def store(docs: DataFrame, id_col: str = "doc_id", text: str = "text", lacing: str = "auto") -> DataFrame:
    """(id, n_bytes, media binary): every text as a Matroska file."""
    kind = docs.schema[id_col].dataType.simpleString()

    def part(batch: pa.RecordBatch) -> pa.RecordBatch:
        body, off = utf8(batch, "_text")
        raw = body.tobytes()
        files = [mux(padded(raw[a:b]), lacing) for a, b in zip(off[:-1].tolist(), off[1:].tolist(), strict=True)]
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.diff(off), pa.int64()), pa.array(files, pa.binary())], [id_col, "n_bytes", "media"])

    return map_parts(docs.select(F.col(id_col), F.col(text).alias("_text")), "_text", part, f"{id_col} {kind}, n_bytes long, media binary")


def packets(media: DataFrame, id_col: str = "doc_id", column: str = "media") -> DataFrame:
    """The packet table: (id, track, timestamp, offset, size, key, cluster, cued, error)."""
    kind = media.schema[id_col].dataType.simpleString()
    names = [id_col, "track", "timestamp", "offset", "size", "key", "cluster", "cued", "error"]

    def part(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows, ids = [], batch.column(0).to_pylist()
        for i, data in zip(ids, batch.column(1).to_pylist(), strict=True):
            if data is None:
                continue
            try:
                m = demux(data)
            except (ValueError, IndexError, struct.error) as e:
                rows.append((i, None, None, None, None, None, None, None, str(e)))
                continue
            cued = {(t, c) for _, t, c in m.cues}
            rows += [(i, p.track, p.timestamp, p.offset, p.size, p.key, p.cluster, (p.track, p.cluster) in cued, None) for p in m.packets]
        cols = list(zip(*rows, strict=True)) if rows else [[]] * len(names)
        types = [batch.schema.field(0).type, pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.bool_(), pa.string()]
        return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, types, strict=True)], names)

    return map_parts(media.select(id_col, column), column, part, f"{id_col} {kind}, track int, timestamp long, offset long, size long, key boolean, cluster long, cued boolean, error string")


_found = pa.struct([("track", pa.int32()), ("timestamp", pa.int64()), ("offset", pa.int64()), ("size", pa.int64()), ("key", pa.bool_()), ("cluster", pa.int64()), ("cued", pa.bool_())])


def indexed(media: DataFrame, column: str = "media") -> DataFrame:
    """All columns of `media` with packets (a list in file order), clusters, cues, duration (ms) and error."""
    names = media.columns

    def part(batch: pa.RecordBatch) -> pa.RecordBatch:
        lists, clusters, cues, durations, errors = [], [], [], [], []
        for data in batch.column(names.index(column)).to_pylist():
            m, error = Media(), None
            if data is not None:
                try:
                    m = demux(data)
                except (ValueError, IndexError, struct.error) as e:
                    m, error = Media(), str(e)
            cued = {(t, c) for _, t, c in m.cues}
            lists.append([{"track": p.track, "timestamp": p.timestamp, "offset": p.offset, "size": p.size, "key": p.key, "cluster": p.cluster, "cued": (p.track, p.cluster) in cued} for p in m.packets])
            clusters.append(m.clusters)
            cues.append(len(m.cues))
            durations.append(m.duration)
            errors.append(error)
        made = [pa.array(lists, pa.list_(_found)), pa.array(clusters, pa.int64()), pa.array(cues, pa.int64()), pa.array(durations, pa.float64()), pa.array(errors, pa.string())]
        return pa.RecordBatch.from_arrays([*batch.columns, *made], [*names, "packets", "clusters", "cues", "duration", "error"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in media.schema)
    schema += ", packets array<struct<track:int,timestamp:bigint,offset:bigint,size:bigint,key:boolean,cluster:bigint,cued:boolean>>, clusters long, cues long, duration double, error string"
    return map_parts(media, column, part, schema)


def ranges(found: DataFrame, id_col: str = "doc_id", track: int = 1, column: str = "media") -> DataFrame:
    """Reads the byte ranges of a track's packets from `indexed` media: digests and features of the payload."""
    kind = found.schema[id_col].dataType.simpleString()
    names = ["n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]

    def part(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = []
        ids, n_bytes, data, lists, clusters, cues, durations = batch.columns
        off, flat = lists.offsets.to_numpy(), lists.values
        tracks, offset, size = (flat.field(k).to_numpy(zero_copy_only=False) for k in ("track", "offset", "size"))
        for k in range(batch.num_rows):
            stored = data[k].as_buffer()
            body, own = memoryview(stored), slice(off[k], off[k + 1])
            back = b"".join([body[a : a + n] for a, n, t in zip(offset[own].tolist(), size[own].tolist(), tracks[own].tolist(), strict=True) if t == track])
            feature = feature_of(int(off[k + 1] - off[k]), clusters[k].as_py(), cues[k].as_py(), durations[k].as_py(), back)
            rows.append((n_bytes[k].as_py(), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-PAD:]), len(body), hashlib.sha256(body).hexdigest(), feature))
        cols = list(zip(*rows, strict=True))
        types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        return pa.RecordBatch.from_arrays([ids, *(pa.array(list(c), t) for c, t in zip(cols, types, strict=True))], [id_col, *names])

    schema = f"{id_col} {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return map_parts(found.select(id_col, "n_bytes", column, "packets", "clusters", "cues", "duration"), column, part, schema)


def roundtrip(docs: DataFrame, id_col: str = "doc_id", text: str = "text", lacing: str = "auto") -> DataFrame:
    """Writes every text as a media column to a table, parses that table into packets and reads their byte ranges back."""
    return ranges(indexed(settle(store(docs, id_col, text, lacing), "media")), id_col)
