"""ISO media containers: a writer for one-track files and a reader that walks their boxes.

The reader descends into container boxes only, decodes the sample tables (sizes, chunk
runs, chunk offsets, durations, sync samples) and reports codec, duration and the byte
range of every keyframe; no payload byte is decoded for that.  Both 32- and 64-bit box
sizes, chunk offsets and durations are read, as are fixed and per-sample sizes.

The query stores each text, zero-padded to a positive multiple of 64 bytes, as a track of
8-bit samples: one access unit is 64 bytes, 16 units make a chunk, and the first unit of each chunk
is marked as a sync sample.

Edge cases: a null or empty text becomes one unit of zeros; equal texts give equal files;
repeated rows give repeated rows; malformed containers raise ``ValueError`` in
:func:`inspect` and give a null row in :func:`describe_media`; all columns except the named
ones are ignored.  An empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import as_bytes, drop_suffix, read_documents, ship

UNIT = 64
UNITS_PER_CHUNK = 16
RATE = 8000
CODEC = b"raw "
#: Box types that hold nothing but boxes.
CONTAINERS = frozenset((b"moov", b"trak", b"mdia", b"minf", b"stbl", b"edts", b"udta"))
DIGEST_SCHEMA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
MEDIA_SCHEMA = "doc_id long, codec string, duration_s double, n_samples long, keyframes array<struct<start:long,end:long>>"


@dataclass(frozen=True)
class Track:
    codec: str
    timescale: int
    duration: int
    sizes: np.ndarray
    starts: np.ndarray
    sync: np.ndarray

    @property
    def keyframes(self) -> np.ndarray:
        """(first byte, end byte) of every sync sample."""
        return np.stack([self.starts[self.sync], self.starts[self.sync] + self.sizes[self.sync]], 1)


def _box(kind: bytes, body: bytes) -> bytes:
    if len(body) + 8 < 1 << 32:
        return struct.pack(">I4s", len(body) + 8, kind) + body
    return struct.pack(">I4sQ", 1, kind, len(body) + 16) + body


def _full(kind: bytes, body: bytes) -> bytes:
    return _box(kind, bytes(4) + body)


def pad(raw: bytes) -> bytes:
    return raw + bytes(-len(raw) % UNIT or (0 if raw else UNIT))


def write_container(payload: bytes) -> bytes:
    """One audio track of 8-bit samples holding ``payload`` unchanged (length: a positive multiple of 64)."""
    units = len(payload) // UNIT
    chunks = -(-units // UNITS_PER_CHUNK)
    last = units - (chunks - 1) * UNITS_PER_CHUNK
    matrix = struct.pack(">9I", 0x10000, 0, 0, 0, 0x10000, 0, 0, 0, 0x40000000)
    runs = [(1, UNITS_PER_CHUNK, 1)] if chunks > 1 else []
    if last != UNITS_PER_CHUNK or chunks == 1:
        runs.append((chunks, last, 1))
    wide = len(payload) > 0xF0000000
    entry = _box(CODEC, bytes(6) + struct.pack(">H8xHHHHI", 1, 1, 8, 0, 0, RATE << 16))
    head = _box(b"ftyp", b"isom" + struct.pack(">I", 512) + b"isomiso2")

    def movie(first: int) -> bytes:
        offsets = np.arange(chunks, dtype=np.int64) * (UNIT * UNITS_PER_CHUNK) + first
        table = _box(
            b"stbl",
            _full(b"stsd", struct.pack(">I", 1) + entry)
            + _full(b"stts", struct.pack(">III", 1, units, UNIT))
            + _full(b"stss", struct.pack(">I", chunks) + (np.arange(chunks) * UNITS_PER_CHUNK + 1).astype(">u4").tobytes())
            + _full(b"stsc", struct.pack(">I", len(runs)) + b"".join(struct.pack(">III", *r) for r in runs))
            + _full(b"stsz", struct.pack(">II", UNIT, units))
            + _full(b"co64" if wide else b"stco", struct.pack(">I", chunks) + offsets.astype(">u8" if wide else ">u4").tobytes()),
        )
        length = min(len(payload), 0xFFFFFFFF)
        info = _full(b"smhd", bytes(4)) + _box(b"dinf", _full(b"dref", struct.pack(">I", 1) + _box(b"url ", b"\0\0\0\1"))) + table
        media = _full(b"mdhd", struct.pack(">IIIIHH", 0, 0, RATE, length, 0x55C4, 0)) + _full(b"hdlr", struct.pack(">I4s12x", 0, b"soun") + b"\0") + _box(b"minf", info)
        track = _full(b"tkhd", struct.pack(">IIIII8xHHHH", 0, 0, 1, 0, length, 0, 0, 0x100, 0) + matrix + bytes(8)) + _box(b"mdia", media)
        return _box(b"moov", _full(b"mvhd", struct.pack(">IIIIIH10x", 0, 0, RATE, length, 0x10000, 0x100) + matrix + bytes(24) + struct.pack(">I", 2)) + _box(b"trak", track))

    start = len(head) + len(movie(0)) + (16 if len(payload) + 8 >= 1 << 32 else 8)
    return head + movie(start) + _box(b"mdat", payload)


#: No container nests its boxes deeper than a few levels; hostile ones do.
DEPTH = 16


def walk(data: bytes, start: int = 0, end: int | None = None, path: tuple[bytes, ...] = ()) -> Iterator[tuple[tuple[bytes, ...], int, int]]:
    """(path of types, body start, body end) of every box, parents before children."""
    end = len(data) if end is None else end
    while start < end:
        if end - start < 8:
            raise ValueError("a box header is cut off")
        length, kind = struct.unpack_from(">I4s", data, start)
        body = start + 8
        if length == 1:
            if end - start < 16:
                raise ValueError("a box header is cut off")
            (length,) = struct.unpack_from(">Q", data, body)
            body += 8
        elif length == 0:
            length = end - start
        if length < body - start or start + length > end:
            raise ValueError(f"box {kind!r} doesn't fit into its parent")
        yield (*path, kind), body, start + length
        if kind in CONTAINERS:
            if len(path) >= DEPTH:
                raise ValueError("boxes are nested too deeply")
            yield from walk(data, body, start + length, (*path, kind))
        start += length


def _table(data: bytes, at: int, end: int, kind: str, width: int) -> np.ndarray:
    (count,) = struct.unpack_from(">I", data, at + 4)
    size = np.dtype(kind).itemsize * width
    if at + 8 + count * size > end:
        raise ValueError("a sample table is cut off")
    return np.frombuffer(data, kind, count * width, at + 8).astype(np.int64).reshape(count, width)


def inspect(data: bytes) -> list[Track]:
    """Every track of a container, from its sample tables alone."""
    tracks: list[dict] = []
    try:
        for path, at, end in walk(data):
            kind = path[-1]
            if kind == b"trak":
                tracks.append({})
            if not tracks or b"trak" not in path:
                continue
            t = tracks[-1]
            if kind == b"mdhd":
                t["time"] = struct.unpack_from(">IQ", data, at + 20) if data[at] == 1 else struct.unpack_from(">II", data, at + 12)
            elif kind == b"stsd":
                t["codec"] = data[at + 12 : at + 16].decode("latin-1")
            elif kind == b"stts":
                t["stts"] = _table(data, at, end, ">u4", 2)
            elif kind == b"stss":
                t["stss"] = _table(data, at, end, ">u4", 1)[:, 0] - 1
            elif kind == b"stsc":
                t["stsc"] = _table(data, at, end, ">u4", 3)
            elif kind == b"stsz":
                fixed, count = struct.unpack_from(">II", data, at + 4)
                if count * max(fixed, 4 if not fixed else 1) > len(data):
                    raise ValueError("more samples than bytes")
                t["sizes"] = np.full(count, fixed, np.int64) if fixed else np.frombuffer(data, ">u4", count, at + 12).astype(np.int64)
            elif kind in (b"stco", b"co64"):
                t["chunks"] = _table(data, at, end, ">u4" if kind == b"stco" else ">u8", 1)[:, 0]
        return [_resolve(t) for t in tracks]
    except (struct.error, KeyError, IndexError) as e:
        raise ValueError(f"not a readable container: {e}") from e


def _resolve(t: dict) -> Track:
    sizes, chunks, runs = t["sizes"], t["chunks"], t["stsc"]
    ends = np.append(runs[1:, 0], len(chunks) + 1)
    if len(runs) and (runs[0, 0] != 1 or (ends <= runs[:, 0]).any() or (runs[:, 1] < 1).any()):
        raise ValueError("the chunk table isn't in order")
    if len(chunks) and ends.max() > len(chunks) + 1:
        raise ValueError("the chunk table names chunks that aren't there")
    per_chunk = np.repeat(runs[:, 1], ends - runs[:, 0])
    if len(per_chunk) != len(chunks) or per_chunk.sum() != len(sizes):
        raise ValueError("the sample tables disagree")
    chunk = np.repeat(np.arange(len(chunks)), per_chunk)
    before = np.cumsum(sizes) - sizes
    first = np.cumsum(per_chunk) - per_chunk
    starts = chunks[chunk] + before - before[first[chunk]]
    timescale, duration = t["time"]
    duration = duration or int((t["stts"][:, 0] * t["stts"][:, 1]).sum())
    sync = t.get("stss", np.arange(len(sizes)))
    return Track(t["codec"], timescale, duration, sizes, starts, sync)


def payload_of(data: bytes, track: Track) -> bytes:
    """The samples' stored bytes, in order."""
    ends = track.starts + track.sizes
    cut = np.flatnonzero(track.starts[1:] != ends[:-1]) + 1
    firsts, lasts = np.append(0, cut), np.append(cut, len(ends)) - 1
    return b"".join(data[a:b] for a, b in zip(track.starts[firsts].tolist(), ends[lasts].tolist(), strict=True))


def _feature(track: Track) -> str:
    keys = track.keyframes
    ranges = zlib.crc32(keys.astype("<i8").tobytes())
    return f"codec={track.codec.strip()};rate={track.timescale};duration={track.duration};samples={len(track.sizes)};keyframes={len(keys)};first={keys[0, 0]}-{keys[0, 1]};last={keys[-1, 0]}-{keys[-1, 1]};ranges_crc32={ranges}"


def _digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = []
        for raw in as_bytes(batch.column(1)):
            stored = write_container(pad(raw))
            (track,) = inspect(stored)
            back = payload_of(stored, track)
            rows.append((len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-UNIT:]), len(stored), hashlib.sha256(stored).hexdigest(), _feature(track)))
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        columns = [list(c) for c in zip(*rows, strict=True)] or [[] for _ in kinds]
        names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
        yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], names)


def _described(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    ranges = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
    for batch in batches:
        codecs, durations, counts, keys = [], [], [], []
        for raw in batch.column(1).to_pylist():
            try:
                track = inspect(raw)[0] if raw else None
            except (ValueError, IndexError):
                track = None
            codecs.append(track and track.codec)
            durations.append(track and track.duration / max(1, track.timescale))
            counts.append(track and len(track.sizes))
            keys.append(track and [{"start": a, "end": b} for a, b in track.keyframes.tolist()])
        yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(codecs, pa.string()), pa.array(durations, pa.float64()), pa.array(counts, pa.int64()), pa.array(keys, ranges)], ["doc_id", "codec", "duration_s", "n_samples", "keyframes"])


def store_texts(docs: DataFrame) -> DataFrame:
    """doc_id, media: the container that holds each whole text."""
    ship(docs.sparkSession)

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array([write_container(pad(x)) for x in as_bytes(batch.column(1))], pa.binary())], ["doc_id", "media"])

    return drop_suffix(docs, ["doc_id", "text"]).mapInArrow(run, "doc_id long, media binary")


def describe_media(media: DataFrame, id_column: str = "doc_id", media_column: str = "media") -> DataFrame:
    """Codec, duration and keyframe byte ranges of a column of containers (first track)."""
    ship(media.sparkSession)
    return media.select(F.col(f"`{id_column}`").alias("doc_id"), F.col(f"`{media_column}`").alias("media")).mapInArrow(_described, MEDIA_SCHEMA)


def op7_media_boxes(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return drop_suffix(read_documents(spark, sf_dir), ["doc_id", "text"]).mapInArrow(_digests, DIGEST_SCHEMA)
