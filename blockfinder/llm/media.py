"""Media columns: ISO base media containers, written and walked without decoding payloads.

``write_container`` stores bytes as raw 8-bit grey frames; ``walk`` and ``track_features`` read any file of nested
boxes and its sample tables; ``media_columns`` does so over a table.
"""

from __future__ import annotations

import hashlib
import json
import struct
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import arrow_map, as_bytes, documents

# Fixed values of the container format: boxes that hold other boxes, and the bytes of their own before those.
NESTED = {b"moov": 0, b"trak": 0, b"mdia": 0, b"minf": 0, b"stbl": 0, b"dinf": 0, b"edts": 0, b"udta": 0, b"mvex": 0, b"moof": 0, b"traf": 0, b"stsd": 8, b"dref": 8}
FRAME = 64  # bytes of a frame: 8 by 8 samples of 8 bits
CHUNK_FRAMES = 256
KEY_EVERY = 16
TIMESCALE = 1000
FRAME_TICKS = 40
UNITY = struct.pack(">9I", 0x10000, 0, 0, 0, 0x10000, 0, 0, 0, 0x40000000)


def box(kind: bytes, *parts: bytes) -> bytes:
    body = b"".join(parts)
    if len(body) + 8 < 1 << 32:
        return struct.pack(">I4s", len(body) + 8, kind) + body
    return struct.pack(">I4sQ", 1, kind, len(body) + 16) + body


def full_box(kind: bytes, *parts: bytes, version: int = 0, flags: int = 0) -> bytes:
    return box(kind, struct.pack(">I", version << 24 | flags), *parts)


def write_container(payload: bytes) -> bytes:
    """Store ``payload`` (a positive multiple of 64 bytes) as grey frames of 8 by 8 samples in one video track.

    Each frame can be decoded by itself; every 16th is listed as a sync sample, so that a reader may seek there.
    """
    if not payload or len(payload) % FRAME:
        raise ValueError(f"the payload must be a positive multiple of {FRAME} bytes")
    frames = len(payload) // FRAME
    chunks = -(-frames // CHUNK_FRAMES)
    last = frames - (chunks - 1) * CHUNK_FRAMES
    duration = frames * FRAME_TICKS
    runs = [(1, CHUNK_FRAMES)] * (chunks > 1) + [(chunks, last)] * (chunks == 1 or last != CHUNK_FRAMES)
    keys = range(1, frames + 1, KEY_EVERY)
    entry = box(b"raw ", bytes(6), struct.pack(">H", 1), bytes(16), struct.pack(">HHII", 8, 8, 72 << 16, 72 << 16), bytes(4), struct.pack(">H", 1), bytes(32), struct.pack(">Hh", 40, -1))

    def movie(first: int) -> bytes:
        tables = box(
            b"stbl",
            full_box(b"stsd", struct.pack(">I", 1), entry),
            full_box(b"stts", struct.pack(">III", 1, frames, FRAME_TICKS)),
            full_box(b"stss", struct.pack(f">I{len(keys)}I", len(keys), *keys)),
            full_box(b"stsc", struct.pack(">I", len(runs)), *[struct.pack(">III", at, n, 1) for at, n in runs]),
            full_box(b"stsz", struct.pack(">II", FRAME, frames)),
            full_box(b"co64", struct.pack(f">I{chunks}Q", chunks, *[first + k * CHUNK_FRAMES * FRAME for k in range(chunks)])),
        )
        information = box(b"minf", full_box(b"vmhd", bytes(8), flags=1), box(b"dinf", full_box(b"dref", struct.pack(">I", 1), full_box(b"url ", flags=1))), tables)
        media = box(b"mdia", full_box(b"mdhd", struct.pack(">QQIQHH", 0, 0, TIMESCALE, duration, 0x55C4, 0), version=1), full_box(b"hdlr", bytes(4), b"vide", bytes(12), b"frames\0"), information)
        track = box(b"trak", full_box(b"tkhd", struct.pack(">QQIIQ", 0, 0, 1, 0, duration), bytes(8), struct.pack(">HHHH", 0, 0, 0, 0), UNITY, struct.pack(">II", 8 << 16, 8 << 16), version=1, flags=7), media)
        return box(b"moov", full_box(b"mvhd", struct.pack(">QQIQ", 0, 0, TIMESCALE, duration), struct.pack(">IHH", 0x10000, 0x100, 0), bytes(8), UNITY, bytes(24), struct.pack(">I", 2), version=1), track)

    head = box(b"ftyp", b"isom", struct.pack(">I", 512), b"isomqt  ")
    data_head = 8 if len(payload) + 8 < 1 << 32 else 16
    size = len(movie(0))
    return head + movie(len(head) + size + data_head) + box(b"mdat", payload)


def walk(data: bytes, start: int = 0, end: int | None = None, path: tuple[bytes, ...] = ()):
    """Yield (path, content start, content end) of every box, outer ones first; a broken box ends its level."""
    end = len(data) if end is None else end
    while start + 8 <= end:
        size, kind = struct.unpack_from(">I4s", data, start)
        head = 8
        if size == 1:
            if start + 16 > end:
                return
            size, head = struct.unpack_from(">Q", data, start + 8)[0], 16
        elif size == 0:
            size = end - start
        if size < head or start + size > end:
            return
        here = (*path, kind)
        yield here, start + head, start + size
        if kind in NESTED:
            yield from walk(data, start + head + NESTED[kind], start + size, here)
        start += size


def table(data: bytes, at: int, end: int, form: str, skip: int = 4) -> list[tuple]:
    """The rows of a counted table; a count that runs past the box is cut there."""
    n = struct.unpack_from(">I", data, at + skip)[0] if at + skip + 4 <= end else 0
    width = struct.calcsize(form)
    n = min(n, max(0, end - at - skip - 4) // width)
    return list(struct.iter_unpack(form, data[at + skip + 4 : at + skip + 4 + n * width]))


def track_features(data: bytes | None) -> list[dict]:
    """Codec, duration and keyframe byte ranges of each track; no track, no rows (null and broken bytes too).

    A track without a table of sync samples has a keyframe at each sample. Samples outside the file are left out.
    """
    tracks: list[dict] = []
    for path, at, end in walk(data or b""):
        kind = path[-1]
        if kind == b"trak":
            tracks.append({"codec": None, "handler": None, "timescale": None, "duration": None, "width": None, "height": None, "sizes": [], "chunks": [], "runs": [], "times": [], "keys": None})
        if not tracks or b"trak" not in path:
            continue
        t = tracks[-1]
        try:
            if kind == b"mdhd":
                t["timescale"], t["duration"] = struct.unpack_from(">IQ", data, at + 20) if data[at] == 1 else struct.unpack_from(">II", data, at + 12)
            elif kind == b"hdlr" and path[-2] == b"mdia":
                t["handler"] = data[at + 8 : at + 12].decode("latin-1")
            elif len(path) > 1 and path[-2] == b"stsd" and t["codec"] is None:
                t["codec"] = kind.decode("latin-1").strip()
                if t["handler"] == "vide":
                    t["width"], t["height"] = struct.unpack_from(">HH", data, at + 24)
            elif kind == b"stsz":
                one = struct.unpack_from(">I", data, at + 4)[0]
                n = struct.unpack_from(">I", data, at + 8)[0]
                t["sizes"] = [one] * min(n, len(data) // one) if one else [x[0] for x in table(data, at, end, ">I", 8)]
            elif kind in (b"stco", b"co64"):
                t["chunks"] = [x[0] for x in table(data, at, end, ">I" if kind == b"stco" else ">Q")]
            elif kind == b"stsc":
                t["runs"] = table(data, at, end, ">III")
            elif kind == b"stts":
                t["times"] = table(data, at, end, ">II")
            elif kind == b"stss":
                t["keys"] = {x[0] for x in table(data, at, end, ">I")}
        except (struct.error, IndexError):
            continue
    for t in tracks:
        ranges, sample, bounds = [], 0, [r[0] for r in t["runs"][1:]] + [len(t["chunks"]) + 1]
        spans = []
        for (first, per, _), stop in zip(t["runs"], bounds, strict=True):
            for chunk in range(first, min(stop, len(t["chunks"]) + 1)):
                offset = t["chunks"][chunk - 1]
                for size in t["sizes"][sample : sample + per]:
                    sample += 1
                    if offset + size <= len(data):
                        spans.append((offset, size))
                        if t["keys"] is None or sample in t["keys"]:
                            ranges.append((offset, size))
                    offset += size
        t["samples"], t["spans"], t["keyframes"] = len(spans), spans, ranges
    return tracks


def read_samples(data: bytes) -> bytes:
    """The bytes of all samples of the first track, in order, by its sample tables."""
    merged: list[list[int]] = []
    for offset, size in track_features(data)[0]["spans"]:
        if merged and merged[-1][1] == offset:
            merged[-1][1] += size
        else:
            merged.append([offset, offset + size])
    return b"".join(data[a:b] for a, b in merged)


TRACKS = "array<struct<codec:string,handler:string,timescale:long,duration:long,width:int,height:int,samples:long,keyframes:array<struct<offset:long,size:long>>>>"


def media_columns(df: DataFrame, key: str, content: str) -> DataFrame:
    """Read the containers in the binary column ``content``: (key, media_bytes, media_sha256, tracks).

    Null and broken content gives no tracks; media_bytes and media_sha256 are null for null. Repeated rows stay.
    """
    kind = pa.list_(pa.struct([("codec", pa.string()), ("handler", pa.string()), ("timescale", pa.int64()), ("duration", pa.int64()), ("width", pa.int32()), ("height", pa.int32()), ("samples", pa.int64()), ("keyframes", pa.list_(pa.struct([("offset", pa.int64()), ("size", pa.int64())])))]))

    def rows(batches):
        for batch in batches:
            contents = batch.column(1).to_pylist()
            found = [[{k: t[k] for k in ("codec", "handler", "timescale", "duration", "width", "height", "samples")} | {"keyframes": [{"offset": a, "size": b} for a, b in t["keyframes"]]} for t in track_features(c)] for c in contents]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([None if c is None else len(c) for c in contents], pa.int64()), pa.array([None if c is None else hashlib.sha256(c).hexdigest() for c in contents]), pa.array(found, kind)],
                ["key", "media_bytes", "media_sha256", "tracks"],
            )

    narrow = df.select(df[key].alias("key"), df[content].alias("content"))
    return arrow_map(narrow, rows, f"key {narrow.schema['key'].dataType.simpleString()}, media_bytes long, media_sha256 string, tracks {TRACKS}")


def text_containers(df: DataFrame, key: str = "doc_id", text: str = "text", keep_media: bool = True) -> DataFrame:
    """Store each text in a container, read it back, and describe both.

    The payload is the UTF-8 text (null: empty) and zero bytes up to a positive multiple of 64. ``feature`` is JSON
    read from the stored boxes: codec, size, timescale, duration, samples, chunks' keyframes (count, first and last byte
    range, and a digest of all ranges). With ``keep_media`` the container itself is the column ``media``.
    """

    def rows(batches):
        for batch in batches:
            out = []
            for payload in as_bytes(batch.column(1)).to_pylist():
                n = len(payload)
                media = write_container(payload + bytes(max(FRAME, -(-n // FRAME) * FRAME) - n))
                track = track_features(media)[0]
                back = read_samples(media)
                keys = track["keyframes"]
                spans = hashlib.sha256(b"".join(struct.pack(">QQ", *k) for k in keys)).hexdigest()
                feature = json.dumps({k: track[k] for k in ("codec", "width", "height", "timescale", "duration", "samples")} | {"keyframes": len(keys), "first": list(keys[0]), "last": list(keys[-1]), "ranges": spans[:16]})
                out.append((n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(media), hashlib.sha256(media).hexdigest(), feature, *[media] * keep_media))
            columns = zip(*out, strict=True)
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), *[pa.binary()] * keep_media]
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(c, k) for c, k in zip(columns, kinds, strict=True)]], [key, *NAMES, *["media"] * keep_media])

    narrow = df.select(df[key], df[text])
    return arrow_map(narrow, rows, f"`{key}` {narrow.schema[0].dataType.simpleString()}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string" + ", media binary" * keep_media)


NAMES = ["n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text_containers(documents(spark, sf_dir), keep_media=False)
