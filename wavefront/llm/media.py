"""ISO media files in a column: write a payload as one track, walk the boxes, read the sample tables back.

Reading never touches payload bytes: the walker visits box headers, the tables give codec, duration and the byte
range of every sync sample; ``payload_of`` then slices the stored bytes by those ranges.
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

UNIT = 576
FILL = b"\xff"
RATE = 8000
KEY_EVERY = 8
CHUNK_SAMPLES = 16
# Boxes that hold boxes.
CONTAINERS = {b"moov", b"trak", b"edts", b"mdia", b"minf", b"dinf", b"stbl", b"mvex", b"moof", b"traf", b"udta"}
_MATRIX = struct.pack(">9I", 0x10000, 0, 0, 0, 0x10000, 0, 0, 0, 0x40000000)


def box(kind: bytes, *parts: bytes) -> bytes:
    body = b"".join(parts)
    if len(body) + 8 < 1 << 32:
        return struct.pack(">I4s", len(body) + 8, kind) + body
    return struct.pack(">I4sQ", 1, kind, len(body) + 16) + body


def full_box(kind: bytes, *parts: bytes, version: int = 0, flags: int = 0) -> bytes:
    return box(kind, struct.pack(">I", version << 24 | flags), *parts)


def pad(data: bytes) -> bytes:
    """Fill up with bytes 255 to a positive multiple of the unit."""
    return data + FILL * (-len(data) % UNIT or (0 if data else UNIT))


def store(payload: bytes) -> bytes:
    """A file with one track of unsigned 8-bit samples, ``UNIT`` bytes to a table entry, chunks of sixteen entries."""
    if not payload or len(payload) % UNIT:
        raise ValueError("the payload must be a positive multiple of the unit")
    n = len(payload) // UNIT
    chunks = -(-n // CHUNK_SAMPLES)
    ticks = n * UNIT
    entry = box(b"raw ", bytes(6), struct.pack(">H", 1), bytes(8), struct.pack(">HHHHI", 1, 8, 0, 0, RATE << 16))
    runs = [(1, CHUNK_SAMPLES, 1)] if n >= CHUNK_SAMPLES else []
    if n % CHUNK_SAMPLES:
        runs.append((chunks, n % CHUNK_SAMPLES, 1))
    keys = range(1, n + 1, KEY_EVERY)
    head = box(b"ftyp", b"isom", struct.pack(">I", 0x200), b"isommp41")

    def moov(first: int) -> bytes:
        table = box(
            b"stbl",
            full_box(b"stsd", struct.pack(">I", 1), entry),
            full_box(b"stts", struct.pack(">III", 1, n, UNIT)),
            full_box(b"stss", struct.pack(f">I{len(keys)}I", len(keys), *keys)),
            full_box(b"stsc", struct.pack(">I", len(runs)), *(struct.pack(">III", *r) for r in runs)),
            full_box(b"stsz", struct.pack(">II", UNIT, n)),
            full_box(b"co64", struct.pack(f">I{chunks}Q", chunks, *range(first, first + len(payload), UNIT * CHUNK_SAMPLES))),
        )
        media = box(
            b"mdia",
            full_box(b"mdhd", struct.pack(">IIIIHH", 0, 0, RATE, ticks & 0xFFFFFFFF, 0x55C4, 0)),
            full_box(b"hdlr", struct.pack(">I4s12x", 0, b"soun"), b"sound\0"),
            box(b"minf", full_box(b"smhd", bytes(4)), box(b"dinf", full_box(b"dref", struct.pack(">I", 1), full_box(b"url ", flags=1))), table),
        )
        track = full_box(b"tkhd", struct.pack(">IIIII8xHHHH", 0, 0, 1, 0, ticks & 0xFFFFFFFF, 0, 0, 0x100, 0), _MATRIX, bytes(8), flags=3)
        movie = full_box(b"mvhd", struct.pack(">IIIIIH10x", 0, 0, RATE, ticks & 0xFFFFFFFF, 0x10000, 0x100), _MATRIX, bytes(24), struct.pack(">I", 2))
        return box(b"moov", movie, box(b"trak", track, media))

    first = len(head) + len(moov(0)) + (8 if len(payload) + 8 < 1 << 32 else 16)
    return head + moov(first) + box(b"mdat", payload)


def walk(data: memoryview, start: int = 0, end: int | None = None, path: tuple[bytes, ...] = ()) -> Iterator[tuple[tuple[bytes, ...], int, int]]:
    """(path, body start, body end) of every box, containers before what they hold. Raises on a box that overruns."""
    end = len(data) if end is None else end
    while start < end:
        if end - start < 8:
            raise ValueError("a box header is cut off")
        size, kind = struct.unpack_from(">I4s", data, start)
        body = start + 8
        if size == 1:
            (size,) = struct.unpack_from(">Q", data, body)
            body += 8
        stop = end if size == 0 else start + size
        if stop > end or stop < body:
            raise ValueError(f"box {kind!r} overruns its parent")
        yield (*path, kind), body, stop
        if kind in CONTAINERS:
            yield from walk(data, body, stop, (*path, kind))
        start = stop


def tracks(data: bytes) -> list[dict]:
    """For each track: codec, timescale, duration, sample offsets and sizes, sync samples and their byte ranges."""
    view = memoryview(data)
    found: list[dict] = []
    for path, a, b in walk(view):
        if path[-2:] == (b"moov", b"trak"):
            found.append({})
        elif found and b"trak" in path:
            found[-1][path[-1]] = (a, b)
    return [_track(view, t) for t in found]


def _track(view: memoryview, t: dict) -> dict:
    version = view[t[b"mdhd"][0]]
    scale, duration = struct.unpack_from(">IQ" if version else ">II", view, t[b"mdhd"][0] + (20 if version else 12))
    codec = bytes(view[t[b"stsd"][0] + 12 : t[b"stsd"][0] + 16]).decode("latin-1")
    same, n = struct.unpack_from(">II", view, t[b"stsz"][0] + 4)
    size = np.full(n, same, np.int64) if same else np.frombuffer(view, ">u4", n, t[b"stsz"][0] + 12).astype(np.int64)
    wide = b"co64" in t
    at = t[b"co64" if wide else b"stco"][0]
    (chunks,) = struct.unpack_from(">I", view, at + 4)
    chunk = np.frombuffer(view, ">u8" if wide else ">u4", chunks, at + 8).astype(np.int64)
    (runs,) = struct.unpack_from(">I", view, t[b"stsc"][0] + 4)
    run = np.frombuffer(view, ">u4", 3 * runs, t[b"stsc"][0] + 8).reshape(-1, 3).astype(np.int64)
    per = np.repeat(run[:, 1], np.diff(np.append(run[:, 0], chunks + 1)))
    which = np.repeat(np.arange(chunks), per)[:n]
    before = np.concatenate(([0], np.cumsum(size)))[:-1]
    first = np.concatenate(([0], np.cumsum(per)))[:-1]
    offset = chunk[which] + before - before[first[which]]
    (steps,) = struct.unpack_from(">I", view, t[b"stts"][0] + 4)
    step = np.frombuffer(view, ">u4", 2 * steps, t[b"stts"][0] + 8).reshape(-1, 2).astype(np.int64)
    sync = np.arange(n)
    if b"stss" in t:
        (k,) = struct.unpack_from(">I", view, t[b"stss"][0] + 4)
        sync = np.frombuffer(view, ">u4", k, t[b"stss"][0] + 8).astype(np.int64) - 1
    return {"codec": codec, "timescale": scale, "duration": duration, "ticks": int((step[:, 0] * step[:, 1]).sum()), "offset": offset, "size": size, "sync": sync, "ranges": np.stack([offset[sync], offset[sync] + size[sync]], axis=1)}


def payload_of(data: bytes, track: dict) -> bytes:
    """The track's samples end to end, read by its tables; runs of adjoining samples are read at once."""
    start, stop = track["offset"], track["offset"] + track["size"]
    cut = np.flatnonzero(start[1:] != stop[:-1]) + 1
    lo, hi = start[np.concatenate(([0], cut))], stop[np.append(cut - 1, len(stop) - 1)]
    return b"".join(data[a:b] for a, b in zip(lo.tolist(), hi.tolist(), strict=True))


_OUT = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, codec string, duration_s double, key_ranges array<struct<start:long,stop:long>>, media binary"


def _stored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows, size = [], 0
        for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            raw = (text or "").encode()
            media = store(pad(raw))
            track = tracks(media)[0]
            back = payload_of(media, track)
            ranges = [{"start": a, "stop": b} for a, b in track["ranges"].tolist()]
            seconds = track["duration"] / track["timescale"]
            feature = f"codec={track['codec']};timescale={track['timescale']};duration={track['duration']};samples={len(track['size'])};keys={len(ranges)};first_key={ranges[0]['start']}-{ranges[0]['stop']};last_key={ranges[-1]['start']}-{ranges[-1]['stop']}"
            rows.append((doc, len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-32:]), len(media), hashlib.sha256(media).hexdigest(), feature, track["codec"], seconds, ranges, media))
            size += 2 * len(media)
            if size > 16 << 20:
                yield _batch(rows)
                rows, size = [], 0
        yield _batch(rows)


_FIELDS = [("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string()), ("codec", pa.string()), ("duration_s", pa.float64()), ("key_ranges", pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))), ("media", pa.binary())]


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    columns = zip(*rows, strict=True) if rows else [[]] * len(_FIELDS)
    return pa.RecordBatch.from_arrays([pa.array(c, kind) for c, (_, kind) in zip(columns, _FIELDS, strict=True)], names=[n for n, _ in _FIELDS])


def as_media(docs: DataFrame) -> DataFrame:
    """Store each whole text of ``docs(doc_id long, text string, ...)`` as an ISO media file and read it back.

    The payload is the UTF-8 text filled up with bytes 255 to a positive multiple of 576. Returns doc_id, sizes and
    digests of what was read back and of the file, ``feature`` and the parsed codec, duration and sync-sample byte
    ranges, and the file itself, a row for each input row. A null text is the empty text; null or repeated doc_ids
    pass through; other columns are ignored; an empty table gives an empty result.
    """
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_stored, _OUT)
