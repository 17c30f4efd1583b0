"""Media columns: payloads in ISO base media containers, and features read from their boxes alone."""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .shared import arrow_map, small_batches, to_batch

FRAME, FRAMES_PER_CHUNK, RATE = 192, 64, 8000
# Boxes nested deeper than this are not entered.
DEEPEST = 32
# Boxes that hold boxes, and the identity matrix of track and movie headers.
CONTAINERS = {b"moov", b"trak", b"mdia", b"minf", b"stbl", b"dinf", b"edts", b"udta", b"mvex", b"moof", b"traf"}
MATRIX = struct.pack(">9i", 0x10000, 0, 0, 0, 0x10000, 0, 0, 0, 0x40000000)


def box(kind: bytes, *parts: bytes) -> bytes:
    size = 8 + sum(map(len, parts))
    head = struct.pack(">I4s", size, kind) if size < 1 << 32 else struct.pack(">I4sQ", 1, kind, size + 8)
    return b"".join([head, *parts])


def full(kind: bytes, *parts: bytes, flags: int = 0) -> bytes:
    return box(kind, struct.pack(">I", flags), *parts)


def pad(data: bytes) -> bytes:
    return data + b" " * (max(1, -(-len(data) // FRAME)) * FRAME - len(data))


def build(payload: bytes) -> bytes:
    """One sound track of 8-bit samples: frames of 192 samples, a sync frame at the start of every chunk."""
    frames = len(payload) // FRAME
    chunks = -(-frames // FRAMES_PER_CHUNK)
    duration = len(payload)
    last = frames - (chunks - 1) * FRAMES_PER_CHUNK
    ftyp = box(b"ftyp", b"isom", struct.pack(">I", 0x200), b"isommp41")
    entry = box(b"raw ", bytes(6), struct.pack(">H", 1), bytes(8), struct.pack(">HHHHI", 1, 8, 0, 0, RATE << 16))
    runs = [(1, FRAMES_PER_CHUNK, 1)] * (chunks > 1 or last == FRAMES_PER_CHUNK) + [(chunks, last, 1)] * (last < FRAMES_PER_CHUNK)
    firsts = np.arange(chunks, dtype=np.int64)

    def moov(data_at: int) -> bytes:
        offsets = data_at + firsts * FRAME * FRAMES_PER_CHUNK
        wide = data_at + len(payload) >= 1 << 32
        places = full(b"co64", struct.pack(">I", chunks), offsets.astype(">u8").tobytes()) if wide else full(b"stco", struct.pack(">I", chunks), offsets.astype(">u4").tobytes())
        tables = [
            full(b"stsd", struct.pack(">I", 1), entry),
            full(b"stts", struct.pack(">III", 1, frames, FRAME)),
            full(b"stsc", struct.pack(">I", len(runs)), b"".join(struct.pack(">III", *r) for r in runs)),
            full(b"stsz", struct.pack(">II", FRAME, frames)),
            places,
            full(b"stss", struct.pack(">I", chunks), (firsts * FRAMES_PER_CHUNK + 1).astype(">u4").tobytes()),
        ]
        sound = box(b"minf", full(b"smhd", bytes(4)), box(b"dinf", full(b"dref", struct.pack(">I", 1), full(b"url ", flags=1))), box(b"stbl", *tables))
        media = box(b"mdia", full(b"mdhd", struct.pack(">IIIIHH", 0, 0, RATE, duration & 0xFFFFFFFF, 0x55C4, 0)), full(b"hdlr", bytes(4), b"soun", bytes(12), b"text\0"), sound)
        track = box(b"trak", full(b"tkhd", struct.pack(">IIIII", 0, 0, 1, 0, duration & 0xFFFFFFFF), bytes(8), struct.pack(">HHHH", 0, 0, 0x100, 0), MATRIX, bytes(8), flags=7), media)
        return box(b"moov", full(b"mvhd", struct.pack(">IIII", 0, 0, RATE, duration & 0xFFFFFFFF), struct.pack(">IH", 0x10000, 0x100), bytes(10), MATRIX, bytes(24), struct.pack(">I", 2)), track)

    head = 8 if len(payload) + 8 < 1 << 32 else 16
    index = moov(0)
    return b"".join([ftyp, moov(len(ftyp) + len(index) + head), box(b"mdat", payload)])


def walk(data):
    """Yields (path, body start, body end) of every box, depth first. Sizes past the end are cut to it; a box that ends before its head does ends its level."""
    todo: list[tuple[int, int, tuple[bytes, ...]]] = [(0, len(data), ())]
    while todo:
        start, end, path = todo.pop()
        if end - start < 8:
            continue
        size, kind = struct.unpack_from(">I4s", data, start)
        head = 8
        if size == 1 and end - start >= 16:
            size, head = struct.unpack_from(">Q", data, start + 8)[0], 16
        stop = end if size == 0 else min(end, start + size)
        if stop < start + head:
            continue
        yield (*path, kind), start + head, stop
        todo.append((stop, end, path))
        if kind in CONTAINERS and len(path) < DEEPEST:
            todo.append((start + head, stop, (*path, kind)))


def _entries(data: bytes, at: int, end: int, count: int, kind: str) -> np.ndarray:
    """Up to ``count`` whole entries of a table that lies between ``at`` and ``end``."""
    dtype = np.dtype(kind)
    return np.frombuffer(data, dtype, max(0, min(count, (end - at) // dtype.itemsize)), min(at, len(data)))


def probe(data: bytes) -> list[dict]:
    """For each track: codec, time scale, duration, frame places and sync frames, from its sample tables.

    Of damaged files, what lies outside a table's box, or frames outside the file, count as absent.
    """
    tracks: list[dict] = []
    none = np.zeros(0, np.int64)
    for path, at, end in walk(data):
        kind = path[-1]
        if kind == b"trak":
            tracks.append({"codec": "", "scale": 1, "duration": 0, "ticks": 0, "sizes": none, "chunks": none, "runs": none.reshape(0, 3), "sync": None})
        if not tracks or b"trak" not in path:
            continue
        t = tracks[-1]
        many = struct.unpack_from(">I", data, at + 4)[0] if end - at >= 8 else 0
        if kind == b"mdhd" and end > at:
            wide = data[at] == 1
            if end - at >= (32 if wide else 20):
                t["scale"], t["duration"] = struct.unpack_from(">IQ" if wide else ">II", data, at + (20 if wide else 12))
                t["scale"] = max(1, t["scale"])
        elif kind == b"stsd" and many and end - at >= 16:
            t["codec"] = data[at + 12 : at + 16].decode("latin-1")
        elif kind == b"stts":
            pairs = _entries(data, at + 8, end, many, "(2,)>u4")
            t["ticks"] = sum(int(n) * int(d) for n, d in pairs)
        elif kind == b"stsc":
            t["runs"] = _entries(data, at + 8, end, many, "(3,)>u4").astype(np.int64)
        elif kind == b"stsz" and end - at >= 12:
            count = struct.unpack_from(">I", data, at + 8)[0]
            t["sizes"] = np.full(min(count, len(data) // many), many, np.int64) if many else _entries(data, at + 12, end, count, ">u4").astype(np.int64)
        elif kind in (b"stco", b"co64"):
            t["chunks"] = np.minimum(_entries(data, at + 8, end, many, ">u4" if kind == b"stco" else ">u8"), np.uint64(len(data))).astype(np.int64)
        elif kind == b"stss":
            t["sync"] = _entries(data, at + 8, end, many, ">u4").astype(np.int64) - 1
    for t in tracks:
        _place_frames(t, len(data))
    return tracks


def _place_frames(t: dict, length: int) -> None:
    """Adds the byte offset of each frame; frames without a chunk, or that end past the file, get no extent."""
    runs, sizes, chunks = t["runs"], t["sizes"], t["chunks"]
    # The number of frames of each chunk is that of the last run that begins at or before it.
    order = np.argsort(runs[:, 0], kind="stable")
    run = np.searchsorted(runs[order, 0], np.arange(1, len(chunks) + 1), side="right") - 1
    per_chunk = np.where(run >= 0, runs[order, 1][np.maximum(run, 0)], 0) if len(runs) else np.zeros(len(chunks), np.int64)
    ends = np.cumsum(np.minimum(per_chunk, len(sizes)))
    frame = np.arange(len(sizes))
    chunk = np.searchsorted(ends, frame, side="right")
    known = chunk < len(chunks)
    before = np.concatenate([[0], np.cumsum(sizes)])
    at = chunk[known]
    offsets = np.zeros(len(sizes), np.int64)
    offsets[known] = chunks[at] + before[:-1][known] - before[np.concatenate([[0], ends])[at]]
    known &= offsets + sizes <= length
    t["offsets"], t["sizes"] = np.where(known, offsets, 0), np.where(known, sizes, 0)
    sync = np.arange(len(sizes)) if t["sync"] is None else t["sync"]
    sync = sync[(sync >= 0) & (sync < len(sizes))]
    t["sync"] = sync[known[sync]]


def sync_ranges(track: dict) -> list[tuple[int, int]]:
    """Byte ranges, end exclusive, of the frames that can be decoded alone."""
    begin = track["offsets"][track["sync"]]
    return list(zip(begin.tolist(), (begin + track["sizes"][track["sync"]]).tolist()))


def read_payload(data: bytes, track: dict) -> bytes:
    """The track's frames in order; neighbouring frames are read together."""
    offsets, ends = track["offsets"], track["offsets"] + track["sizes"]
    if not len(offsets):
        return b""
    cuts = np.flatnonzero(offsets[1:] != ends[:-1]) + 1
    return b"".join(data[a:b] for a, b in zip(offsets[np.concatenate([[0], cuts])], ends[np.concatenate([cuts - 1, [len(ends) - 1]])]))


def features(tracks: list[dict]) -> str:
    """Codec, seconds, frames, sync frames and the first and last sync byte range of each track."""
    told = []
    for t in tracks:
        ranges = sync_ranges(t)
        ends = f";first={ranges[0][0]}-{ranges[0][1]};last={ranges[-1][0]}-{ranges[-1][1]}" if ranges else ""
        told.append(f"codec={t['codec'].strip()};seconds={t['ticks'] / t['scale']:.6f};frames={len(t['sizes'])};sync={len(ranges)}{ends}")
    return "|".join(told)


def store(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes and ``media``: each whole text (null: empty), padded, in a container. Repeated ids come out as often, an empty table gives no rows."""

    def run(batches):
        for batch in small_batches(batches):
            raw = [(t or "").encode() for t in batch.column(1).to_pylist()]
            yield to_batch({"doc_id": batch.column(0), "n_bytes": pa.array([len(r) for r in raw], pa.int64()), "media": pa.array([build(pad(r)) for r in raw], pa.binary())})

    return arrow_map(docs.select("doc_id", "text"), run, "doc_id long, n_bytes long, media binary")


def describe(media: DataFrame) -> DataFrame:
    """Reads containers back: payload size, digests, box features, and in ``keyframes`` all byte ranges of frames that can be decoded alone.

    Null containers are read as empty, damaged ones as far as they go. An empty table gives no rows; other columns play no part.
    """

    def run(batches):
        for batch in small_batches(batches):
            out: dict[str, list] = {k: [] for k in ("payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature")}
            keyframes = []
            for data in batch.column(2).to_pylist():
                data = data or b""
                tracks = probe(data)
                payload = b"".join(read_payload(data, t) for t in tracks)
                for k, v in zip(out, (len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(data), hashlib.sha256(data).hexdigest(), features(tracks))):
                    out[k].append(v)
                keyframes.append([{"start": a, "end": b} for t in tracks for a, b in sync_ranges(t)])
            kinds = {"payload_sha256": pa.string(), "media_sha256": pa.string(), "feature": pa.string()}
            ranges = pa.array(keyframes, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))
            yield to_batch({"doc_id": batch.column(0), "n_bytes": batch.column(1)} | {k: pa.array(v, kinds.get(k, pa.int64())) for k, v in out.items()} | {"keyframes": ranges})

    return arrow_map(media.select("doc_id", "n_bytes", "media"), run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, keyframes array<struct<start:long,end:long>>")
