"""Media columns in ISO base media files: write, walk boxes, decode sample tables, read payloads back.

``wrap`` stores a payload as 8-bit unsigned mono audio ('raw ') in a file with
one track; ``walk`` parses any nesting of boxes (32-bit, 64-bit and to-the-end
sizes); ``tracks`` decodes the sample tables of every track and gives codec,
time scale, duration and the byte range of every sample and keyframe, without
touching the payload; ``payload`` concatenates the ranges. ``store`` makes the
media columns of texts, ``describe`` those of media files from elsewhere.

A sample is a block of 576 bytes; every 8th one is a keyframe. A null text is
stored as an empty one. Equal texts give equal files: no clocks in headers.
Defined results for foreign bytes: a track whose tables are missing, cut off or
point outside the file is left out; bytes without any track, or null, give no
rows of ``describe``; samples of fragments (``moof``) are not listed, as they
have no sample tables; composition offsets (``ctts``) don't move bytes and are
skipped. The codec is the first sample entry's.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphweld.llm.common import map_slices

BLOCK, RATE, KEY_EVERY, PER_CHUNK = 576, 8000, 8, 32
SPANS = "array<struct<start:long,end:long>>"
#: Boxes that hold boxes.
CONTAINERS = frozenset((b"moov", b"trak", b"mdia", b"minf", b"stbl", b"dinf", b"edts", b"mvex", b"moof", b"traf", b"udta"))
#: The unity matrix of the header boxes.
UNITY = struct.pack(">9I", 0x10000, 0, 0, 0, 0x10000, 0, 0, 0, 0x40000000)


def pad(text: bytes) -> bytes:
    return text + b"\xff" * (-len(text) % BLOCK if text else BLOCK)


def box(kind: bytes, *parts: bytes) -> bytes:
    body = b"".join(parts)
    if len(body) + 8 < 1 << 32:
        return struct.pack(">I4s", len(body) + 8, kind) + body
    return struct.pack(">I4sQ", 1, kind, len(body) + 16) + body


def full(kind: bytes, *parts: bytes, version: int = 0, flags: int = 0) -> bytes:
    return box(kind, struct.pack(">I", version << 24 | flags), *parts)


def wrap(data: bytes) -> bytes:
    """The payload, a positive multiple of 576 bytes, as a file."""
    n = len(data) // BLOCK
    keys = range(1, n + 1, KEY_EVERY)
    whole, rest = divmod(n, PER_CHUNK)
    runs = [(1, PER_CHUNK, 1)] * (whole > 0) + [(whole + 1, rest, 1)] * (rest > 0)
    ftyp = box(b"ftyp", b"isom", struct.pack(">I", 512), b"isommp41")
    entry = box(b"raw ", b"\0" * 6, struct.pack(">HQHHHHI", 1, 0, 1, 8, 0, 0, RATE << 16))

    def moov(first: int) -> bytes:
        at = [first + i * PER_CHUNK * BLOCK for i in range(whole + (rest > 0))]
        wide = bool(at) and at[-1] >= 1 << 32
        table = box(
            b"stbl",
            full(b"stsd", struct.pack(">I", 1), entry),
            full(b"stts", struct.pack(">3I", 1, n, BLOCK)),
            full(b"stss", struct.pack(f">I{len(keys)}I", len(keys), *keys)),
            full(b"stsz", struct.pack(">2I", BLOCK, n)),
            full(b"stsc", struct.pack(">I", len(runs)), *(struct.pack(">3I", *r) for r in runs)),
            full(b"co64" if wide else b"stco", struct.pack(f">I{len(at)}{'Q' if wide else 'I'}", len(at), *at)),
        )
        long = n * BLOCK >= 1 << 32
        time = struct.pack(">QQIQ" if long else ">4I", 0, 0, RATE, n * BLOCK)
        track_time = struct.pack(">QQIIQ" if long else ">5I", 0, 0, 1, 0, n * BLOCK)
        return box(
            b"moov",
            full(b"mvhd", time, struct.pack(">IHHQ", 0x10000, 0x100, 0, 0), UNITY, b"\0" * 24, struct.pack(">I", 2), version=int(long)),
            box(
                b"trak",
                full(b"tkhd", track_time, struct.pack(">QHHHH", 0, 0, 0, 0x100, 0), UNITY, struct.pack(">2I", 0, 0), version=int(long), flags=3),
                box(
                    b"mdia",
                    full(b"mdhd", time, struct.pack(">HH", 0x55C4, 0), version=int(long)),
                    full(b"hdlr", b"\0" * 4, b"soun", b"\0" * 13),
                    box(b"minf", full(b"smhd", b"\0" * 4), box(b"dinf", full(b"dref", struct.pack(">I", 1), full(b"url ", flags=1))), table),
                ),
            ),
        )

    head = 16 if len(data) + 8 >= 1 << 32 else 8
    start = len(ftyp) + len(moov(0)) + head
    index = moov(start)
    if len(ftyp) + len(index) + head != start:  # offsets became 64 bits wide
        start = len(ftyp) + len(index) + head
        index = moov(start)
    return b"".join((ftyp, index, box(b"mdat", data)))


def walk(file: bytes, start: int = 0, end: int | None = None, path: tuple = ()):
    """(path, start, end) of the body of every box, depth first; stops at a box that doesn't fit."""
    end = len(file) if end is None else end
    while start + 8 <= end:
        size, kind = struct.unpack_from(">I4s", file, start)
        body = start + 8
        if size == 1:
            if start + 16 > end:
                return
            (size,) = struct.unpack_from(">Q", file, body)
            body += 8
        stop = end if size == 0 else start + size
        if stop > end or stop < body:
            return
        yield (*path, kind), body, stop
        if kind in CONTAINERS:
            yield from walk(file, body, stop, (*path, kind))
        start = stop


def decode(file: bytes, found: dict[bytes, tuple[int, int]]) -> dict:
    """Codec, time scale, duration and sample byte ranges from the boxes of one track. Raises an error where they are broken."""

    def numbers(kind: bytes, code: str = "I", width: int = 1) -> list[tuple]:
        if kind not in found:
            return []
        a, end = found[kind]
        (n,) = struct.unpack_from(">I", file, a + 4)
        size = struct.calcsize(f">{width}{code}")
        if a + 8 + n * size > end:
            raise ValueError("table beyond its box")
        return list(struct.iter_unpack(f">{width}{code}", file[a + 8 : a + 8 + n * size]))

    a = found[b"mdhd"][0]
    scale, duration = struct.unpack_from(">IQ", file, a + 20) if file[a] else struct.unpack_from(">2I", file, a + 12)
    codec = file[found[b"stsd"][0] + 12 : found[b"stsd"][0] + 16].decode("latin-1")
    a, end = found[b"stsz"]
    same, n = struct.unpack_from(">2I", file, a + 4)
    if not same and a + 12 + 4 * n > end:
        raise ValueError("table beyond its box")
    sizes = None if same else [x for (x,) in struct.iter_unpack(">I", file[a + 12 : a + 12 + 4 * n])]
    chunks = [x for (x,) in (numbers(b"co64", "Q") or numbers(b"stco"))]
    runs = numbers(b"stsc", width=3)
    ranges: list[tuple[int, int]] = []
    for k, (first, per, _) in enumerate(runs):
        last = runs[k + 1][0] - 1 if k + 1 < len(runs) else len(chunks)
        for c in range(first - 1, last):
            at = chunks[c]
            for _ in range(min(per, n - len(ranges))):
                size = same or sizes[len(ranges)]
                if at + size > len(file):
                    raise ValueError("sample beyond the file")
                ranges.append((at, at + size))
                at += size
    if len(ranges) < n:
        raise ValueError("samples without chunks")
    sync = [x - 1 for (x,) in numbers(b"stss")] if b"stss" in found else range(n)
    return {"codec": codec, "scale": scale, "duration": duration, "ranges": ranges, "keyframes": [ranges[i] for i in sync], "times": numbers(b"stts", width=2)}


def tracks(file: bytes) -> list[dict]:
    """Every track that can be decoded, in file order."""
    groups: list[dict[bytes, tuple[int, int]]] = []
    for path, a, b in walk(file):
        if path[-1] == b"trak":
            groups.append({})
        elif b"trak" in path:
            groups[-1].setdefault(path[-1], (a, b))
    out = []
    for found in groups:
        try:
            out.append(decode(file, found))
        except (KeyError, IndexError, ValueError, struct.error):  # tables that are missing, cut off or out of bounds
            continue
    return out


def track(file: bytes) -> dict | None:
    """The first track that has samples, else the first one; None if there is none."""
    every = tracks(file)
    return next((t for t in every if t["ranges"]), every[0] if every else None)


def seconds(info: dict) -> float | None:
    return info["duration"] / info["scale"] if info["scale"] else None


def spans(ranges: list[tuple[int, int]]) -> list[dict]:
    return [{"start": a, "end": b} for a, b in ranges]


def describe(media: DataFrame) -> DataFrame:
    """One row per track of each file of ``media`` (id, media binary): codec, seconds, number of samples and keyframe byte ranges."""

    def make():
        def work(part):
            out: dict[str, list] = {k: [] for k in ("owner", "track", "codec", "seconds", "samples", "keyframes")}
            for i, file in enumerate(part.column("media").to_pylist()):
                for k, info in enumerate(tracks(file or b"")):
                    for c, v in zip(out, (i, k, info["codec"], seconds(info), len(info["ranges"]), spans(info["keyframes"])), strict=True):
                        out[c].append(v)
            return out | {"id": part.column("id").take(pa.array(out["owner"], pa.int64()))}

        return work

    kind = dict(media.dtypes)["id"]
    return map_slices(media.select("id", "media"), "media", make, f"id {kind}, track int, codec string, seconds double, samples long, keyframes {SPANS}")


def payload(file: bytes, info: dict) -> bytes:
    return b"".join(file[a:b] for a, b in info["ranges"])


def feature(file: bytes, info: dict) -> str:
    """Codec, duration in seconds, samples, keyframes, their byte span and a digest of all keyframe ranges."""
    keys = info["keyframes"]
    digest = zlib.crc32(b"".join(struct.pack(">2Q", *r) for r in keys))
    return f"codec={info['codec'].strip()};seconds={seconds(info):.3f};samples={len(info['ranges'])};keyframes={len(keys)};span={keys[0][0]}-{keys[-1][1]};ranges={digest:08x}"


def store(documents: DataFrame, with_media: bool = False) -> DataFrame:
    """One row per document: sizes, digests, features, codec, duration and keyframe byte ranges of its media file, and the file itself on demand."""

    def make():
        def work(part):
            out: dict[str, list] = {k: [] for k in ("n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "codec", "seconds", "keyframes", "media")}
            for text in part.column("body").to_pylist():
                text = text or b""
                file = wrap(pad(text))
                info = track(file)
                back = payload(file, info)
                row = (len(text), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-32:]), len(file), hashlib.sha256(file).hexdigest(), feature(file, info), info["codec"].strip(), seconds(info), spans(info["keyframes"]), file)
                for k, v in zip(out, row, strict=True):
                    out[k].append(v)
            return out | {"doc_id": part.column("doc_id")}

        return work

    kind = dict(documents.dtypes)["doc_id"]
    schema = f"doc_id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, codec string, seconds double, keyframes {SPANS}" + ", media binary" * with_media
    return map_slices(documents.select("doc_id", F.col("text").cast("binary").alias("body")), "body", make, schema)
