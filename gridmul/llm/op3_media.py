"""Media columns: ISO media containers.

A payload is stored losslessly as the samples of one uncompressed 8-bit grey video track (frames of 8 x 8 bytes); any
container, ours or foreign, is described by walking its nested boxes and decoding the sample tables: codec, duration and
the byte ranges of its keyframes. Payloads are never decoded.

A track's samples come from its sample tables and from the runs of movie fragments (`moof`), whose sizes, durations and flags
fall back on the fragment's and the movie's defaults; the first track with samples is the one that the columns describe, and
`tracks` tells codec, kind, duration and number of samples of every track. Counts in tables are held against the bytes that
stand behind them before anything of that size is made, so a false count is an error of its row.

Defined cases: null text is empty text; an empty payload is padded to one frame of zeros; very long texts take 64-bit chunk
offsets where 32 bits end; repeated rows and equal texts give equal values; of several tracks the first in the file counts; a
container that is null, truncated, not ISO media, or whose tables claim more than the file holds gives a description whose
fields are null and whose `error` says why; an empty table gives an empty result; extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridmul.llm.common import map_rows, text_of

FRAME = 64
TIMESCALE = 25
KEY_EVERY = 8
CHUNK_FRAMES = 16

#: Boxes whose body is a list of boxes (fixed values of ISO/IEC 14496-12).
CONTAINERS = frozenset([b"moov", b"trak", b"mdia", b"minf", b"stbl", b"dinf", b"edts", b"udta", b"mvex", b"moof", b"traf"])


def _box(kind: bytes, *parts: bytes) -> bytes:
    body = b"".join(parts)
    return struct.pack(">I4s", 8 + len(body), kind) + body


def _full(kind: bytes, *parts: bytes, version: int = 0, flags: int = 0) -> bytes:
    return _box(kind, struct.pack(">I", version << 24 | flags), *parts)


_MATRIX = struct.pack(">9I", 0x10000, 0, 0, 0, 0x10000, 0, 0, 0, 0x40000000)


def pad(data: bytes) -> bytes:
    """Zero bytes up to a positive multiple of the frame size."""
    return data + bytes(-len(data) % FRAME or (0 if data else FRAME))


def pack(payload: bytes) -> bytes:
    """A container holding `payload` (a positive multiple of 64 bytes) as 8 x 8 grey frames, a keyframe in every eight."""
    frames = len(payload) // FRAME
    chunks = -(-frames // CHUNK_FRAMES)
    entry = _box(b"raw ", bytes(6), struct.pack(">H", 1), bytes(16), struct.pack(">HHIIIH", 8, 8, 0x480000, 0x480000, 0, 1), bytes(32), struct.pack(">Hh", 8, -1))
    runs = [(1, CHUNK_FRAMES, 1)] if frames >= CHUNK_FRAMES else []
    if frames % CHUNK_FRAMES:
        runs.append((chunks, frames % CHUNK_FRAMES, 1))
    keys = np.arange(1, frames + 1, KEY_EVERY, dtype=">u4").tobytes()

    def moov(first: int) -> bytes:
        wide = first + len(payload) >= 1 << 32
        offsets = (first + np.arange(chunks, dtype=np.int64) * FRAME * CHUNK_FRAMES).astype(">u8" if wide else ">u4").tobytes()
        table = _box(
            b"stbl",
            _full(b"stsd", struct.pack(">I", 1), entry),
            _full(b"stts", struct.pack(">III", 1, frames, 1)),
            _full(b"stss", struct.pack(">I", len(keys) // 4), keys),
            _full(b"stsc", struct.pack(">I", len(runs)), *(struct.pack(">III", *r) for r in runs)),
            _full(b"stsz", struct.pack(">II", FRAME, frames)),
            _full(b"co64" if wide else b"stco", struct.pack(">I", chunks), offsets),
        )
        media = _box(
            b"mdia",
            _full(b"mdhd", struct.pack(">IIIIHH", 0, 0, TIMESCALE, frames, 0x55C4, 0)),
            _full(b"hdlr", bytes(4), b"vide", bytes(12), b"\0"),
            _box(b"minf", _full(b"vmhd", bytes(8), flags=1), _box(b"dinf", _full(b"dref", struct.pack(">I", 1), _full(b"url ", flags=1))), table),
        )
        track = _box(b"trak", _full(b"tkhd", struct.pack(">IIIII", 0, 0, 1, 0, frames), bytes(16), _MATRIX, struct.pack(">II", 8 << 16, 8 << 16), flags=3), media)
        head = _full(b"mvhd", struct.pack(">IIIIIH", 0, 0, TIMESCALE, frames, 0x10000, 0x100), bytes(10), _MATRIX, bytes(24), struct.pack(">I", 2))
        return _box(b"moov", head, track)

    brand = _box(b"ftyp", b"isom", struct.pack(">I", 0x200), b"isomiso2")
    first = len(brand) + len(moov(0)) + 8
    return brand + moov(first) + _box(b"mdat", payload)


def walk(data: bytes, start: int = 0, end: int | None = None, path: tuple[bytes, ...] = ()) -> Iterator[tuple[tuple[bytes, ...], int, int]]:
    """(path, body start, body end) of every box, parents before children; ValueError on a box that leaves its parent."""
    end = len(data) if end is None else end
    at = start
    while at + 8 <= end:
        size, kind = struct.unpack_from(">I4s", data, at)
        head = 8
        if size == 1:
            if at + 16 > end:
                raise ValueError("box header cut off")
            size, head = struct.unpack_from(">Q", data, at + 8)[0], 16
        elif size == 0:
            size = end - at
        if size < head or at + size > end:
            raise ValueError(f"box {kind!r} of {size} bytes at {at} leaves its parent")
        here = (*path, kind)
        yield here, at + head, at + size
        if kind in CONTAINERS and len(path) < 16:
            yield from walk(data, at + head, at + size, here)
        at += size
    if at != end and path and end - at >= 8:
        raise ValueError("bytes left over in a box")


def _count(data: bytes, at: int, end: int, each: int) -> int:
    n = struct.unpack_from(">I", data, at + 4)[0]
    if at + 8 + n * each > end:
        raise ValueError("a sample table is cut off")
    return n


def _uint(data: bytes, at: int, end: int, wide: bool = False) -> int:
    if at + (8 if wide else 4) > end:
        raise ValueError("a field is cut off")
    return int.from_bytes(data[at : at + (8 if wide else 4)], "big")


def _defaults(data: bytes, at: int, end: int) -> dict:
    """Duration, size and flags of samples by a track fragment's header, where it has them."""
    flags, here, out = _uint(data, at, end) & 0xFFFFFF, at + 8 + 8 * (data[at + 3] & 1), {"track": _uint(data, at + 4, end)}
    if flags & 1:
        out["base"] = _uint(data, at + 8, end, wide=True)
    for bit, name in ((2, None), (8, "duration"), (16, "size"), (32, "flags")):
        if flags & bit:
            if name:
                out[name] = _uint(data, here, end)
            here += 4
    return out


def _run(data: bytes, at: int, end: int, given: dict) -> tuple[int | None, np.ndarray, np.ndarray, np.ndarray]:
    """(offset from the base, sizes, durations, whether a keyframe) of a track run."""
    flags, n, here = _uint(data, at, end) & 0xFFFFFF, _uint(data, at + 4, end), at + 8
    offset = None
    if flags & 1:
        offset = struct.unpack_from(">i", data, here)[0]
        here += 4
    first = None
    if flags & 4:
        first = _uint(data, here, end)
        here += 4
    fields = [f for bit, f in ((0x100, "duration"), (0x200, "size"), (0x400, "flags"), (0x800, "shift")) if flags & bit]
    if here + 4 * n * len(fields) > end or not fields and n * max(given.get("size", 0), 1) > len(data):
        raise ValueError("a track run is cut off")
    table = np.frombuffer(data, ">u4", n * len(fields), here).astype(np.int64).reshape(n, len(fields))
    column = {f: table[:, fields.index(f)] if f in fields else np.full(n, given.get(f, 0), np.int64) for f in ("duration", "size", "flags")}
    kinds = column["flags"].copy()
    if first is not None and n:
        kinds[0] = first
    return offset, column["size"], column["duration"], kinds & 0x10000 == 0


def _table_samples(t: dict, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(offsets, sizes, whether keyframes, ticks) by the sample tables of a track."""
    sizes = t["sizes"]
    if isinstance(sizes, tuple):
        if sizes[0] * sizes[1] > length:
            raise ValueError("samples outside the file")
        sizes = np.full(sizes[1], sizes[0], np.int64)
    n = len(sizes)
    chunks = t.get(b"stco", t.get(b"co64", np.zeros(0, np.int64)))
    runs = t.get(b"stsc", np.zeros(0, np.int64)).reshape(-1, 3)
    counts = np.zeros(len(chunks), np.int64)
    for k, (first, per, _) in enumerate(runs):
        if first < 1 or per < 0:
            raise ValueError("a chunk run is out of place")
        # no chunk has more samples than there are sizes, whatever the table claims
        counts[first - 1 : (runs[k + 1][0] - 1 if k + 1 < len(runs) else len(chunks))] = min(int(per), n)
    ends = np.minimum(np.cumsum(counts), n)
    if n and (not len(ends) or ends[-1] < n):
        raise ValueError("fewer samples in chunks than sizes")
    counts = np.diff(ends, prepend=0)
    chunk = np.repeat(np.arange(len(chunks)), counts)
    before = np.concatenate(([0], np.cumsum(sizes)[:-1])) if n else sizes
    offsets = chunks[chunk] + before - before[np.minimum((ends - counts)[chunk], max(n - 1, 0))]
    keys = np.zeros(n, bool)
    marked = t[b"stss"] - 1 if b"stss" in t else np.arange(n)
    keys[marked[(marked >= 0) & (marked < n)]] = True
    ticks = int((t[b"stts"].reshape(-1, 2).astype(object).prod(axis=1)).sum()) if b"stts" in t and len(t[b"stts"]) else t.get("ticks", 0)
    return offsets, sizes, keys, ticks


def tracks_of(data: bytes | None) -> list[dict]:
    """codec, handler, timescale, duration, samples (offsets, sizes) and keys (indices) of every track, in the file's order."""
    if not data:
        raise ValueError("no bytes")
    tracks: list[dict] = []
    extends: dict[int, dict] = {}
    fragment: dict = {}
    for path, at, end in walk(data):
        kind = path[-1]
        if kind == b"trak":
            tracks.append({"parts": []})
        elif kind == b"trex":
            extends[_uint(data, at + 4, end)] = {"duration": _uint(data, at + 12, end), "size": _uint(data, at + 16, end), "flags": _uint(data, at + 20, end)}
        elif kind == b"moof":
            # the box begins eight or sixteen bytes before its body
            fragment = {"start": at - (16 if data[at - 12 : at - 8] == b"moof" else 8), "next": None}
        elif kind == b"tfhd" and fragment:
            own = _defaults(data, at, end)
            fragment["given"] = extends.get(own["track"], {}) | own
            fragment["base"] = own.get("base", fragment["start"])
            fragment["next"] = fragment["base"]
        elif kind == b"trun" and fragment.get("given"):
            offset, sizes, durations, keys = _run(data, at, end, fragment["given"])
            begin = fragment["next"] if offset is None else fragment["base"] + offset
            fragment["next"] = begin + int(sizes.sum())
            for t in tracks:
                if t.get("id") == fragment["given"]["track"]:
                    t["parts"].append((begin + np.concatenate(([0], np.cumsum(sizes)[:-1])) if len(sizes) else sizes, sizes, keys, int(durations.sum())))
        elif not tracks or b"moov" not in path:
            continue
        elif kind == b"tkhd":
            tracks[-1]["id"] = _uint(data, at + (20 if data[at] == 1 else 12), end)
        elif kind == b"mdhd":
            wide = data[at] == 1
            tracks[-1]["scale"], tracks[-1]["ticks"] = struct.unpack_from(">IQ" if wide else ">II", data, at + (20 if wide else 12))
        elif kind == b"hdlr":
            tracks[-1]["handler"] = data[at + 8 : at + 12].decode("latin-1")
        elif kind == b"stsd":
            if _count(data, at, end, 8):
                tracks[-1]["codec"] = data[at + 12 : at + 16].decode("latin-1")
        elif kind in (b"stts", b"stsc", b"stss", b"stco", b"co64", b"ctts"):
            width = {b"stts": 8, b"stsc": 12, b"stss": 4, b"stco": 4, b"co64": 8, b"ctts": 8}[kind]
            n = _count(data, at, end, width)
            tracks[-1][kind] = np.frombuffer(data, ">u8" if kind == b"co64" else ">u4", n * width // (8 if kind == b"co64" else 4), at + 8).astype(np.int64)
        elif kind == b"stsz":
            same, n = struct.unpack_from(">II", data, at + 4)
            if not same and at + 12 + 4 * n > end:
                raise ValueError("a sample table is cut off")
            tracks[-1]["sizes"] = (same, n) if same else np.frombuffer(data, ">u4", n, at + 12).astype(np.int64)
    out = []
    for t in tracks:
        parts = ([_table_samples(t, len(data))] if "sizes" in t else []) + t["parts"]
        offsets, sizes, keys = (np.concatenate([p[k] for p in parts]) if parts else np.zeros(0, np.int64) for k in range(3))
        if len(sizes) and (offsets.min() < 0 or (offsets + sizes).max() > len(data)):
            raise ValueError("samples outside the file")
        scale = t.get("scale") or 1
        out.append({"codec": t.get("codec"), "handler": t.get("handler"), "timescale": scale, "duration": sum(p[3] for p in parts) / scale, "samples": (offsets, sizes), "keys": np.flatnonzero(keys)})
    return out


def describe(data: bytes | None) -> dict:
    """The first track that has samples (see tracks_of), with the list of all tracks."""
    tracks = tracks_of(data)
    for t in tracks:
        if len(t["samples"][1]):
            return t | {"tracks": tracks}
    raise ValueError("no track with samples")


def read_back(data: bytes, samples: tuple[np.ndarray, np.ndarray]) -> bytes:
    """The stored sample bytes, in order; neighbouring samples are read in one piece."""
    offsets, sizes = samples
    if not len(offsets):
        return b""
    cut = np.flatnonzero(offsets[1:] != offsets[:-1] + sizes[:-1]) + 1
    return b"".join(data[offsets[a] : offsets[b - 1] + sizes[b - 1]] for a, b in zip([0, *cut.tolist()], [*cut.tolist(), len(offsets)]))


def store_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_bytes, media): each text's UTF-8 bytes, padded, as a container."""

    def rows(source):
        for key, text in source:
            raw = text.encode("utf-8")
            yield key, len(raw), pack(pad(raw))

    return map_rows(docs, [F.col(id_col).cast("long").alias("doc_id"), text_of(text_col)], "doc_id long, n_bytes long, media binary", rows)


DESCRIPTION = "tracks array<struct<codec:string,handler:string,duration:double,n_samples:long>>, codec string, handler string, timescale long, duration double, n_samples long, keyframes array<struct<offset:long,length:long>>, error string"


def describe_media(df: DataFrame, id_col: str, media_col: str) -> DataFrame:
    """(id, tracks, codec, handler, timescale, duration in seconds, n_samples, keyframes, error) of any column of containers."""

    def rows(source):
        for key, data in source:
            try:
                d = describe(data)
                o, s = d["samples"]
                tracks = [{"codec": t["codec"], "handler": t["handler"], "duration": t["duration"], "n_samples": len(t["samples"][1])} for t in d["tracks"]]
                yield key, tracks, d["codec"], d["handler"], d["timescale"], d["duration"], len(o), [{"offset": int(o[k]), "length": int(s[k])} for k in d["keys"]], None
            except (ValueError, struct.error, IndexError, OverflowError, MemoryError) as e:
                yield key, None, None, None, None, None, None, None, str(e)

    return map_rows(df, [F.col(id_col).cast("long").alias("id"), F.col(media_col)], f"id long, {DESCRIPTION}", rows)


def digest_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The contract's digest of every text: stored as a container, walked, read back, hashed; one pass, no shuffle."""

    def rows(source):
        for key, text in source:
            raw = text.encode("utf-8")
            media = pack(pad(raw))
            d = describe(media)
            offsets, sizes = d["samples"]
            back = read_back(media, (offsets, sizes))
            ranges = np.stack((offsets[d["keys"]], sizes[d["keys"]]), axis=1)
            spans = hashlib.sha256(",".join(f"{o}+{n}" for o, n in ranges.tolist()).encode()).hexdigest()
            feature = f"codec={d['codec'].strip()};timescale={d['timescale']};frames={len(sizes)};keyframes={len(ranges)};first={ranges[0][0]}+{ranges[0][1]};ranges={spans}"
            yield key, len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-FRAME:]), len(media), hashlib.sha256(media).hexdigest(), feature, d["codec"], d["duration"], len(ranges)

    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, codec string, duration double, n_keyframes long"
    return map_rows(docs, [F.col(id_col).cast("long").alias("doc_id"), text_of(text_col)], schema, rows)
