"""Media columns: ISO base media containers, written and read without decoding what they carry.

The writer lays bytes down as unsigned 8-bit samples in frames of ``FRAME`` bytes, with sample tables and a sync table. The reader walks nested boxes,
decodes the sample tables and gives codec, time scale, duration, number of frames and the byte ranges of key frames; payload bytes are only sliced.

Defined results: a null or empty text is one frame of padding; bytes that are no container, or whose tables disagree with each other or with the
file's length, give null fields and never fail; null media give null fields; a null doc_id and repeated rows are carried through; other columns are ignored.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import columns
from .piece_bpe import slices
from .staging import Staging, ship

FRAME, PAD = 576, b"\xff"
RATE, GROUP = 8000, 8  # samples a second; frames a chunk, of which the first is a key frame
CONTAINERS = {b"moov", b"trak", b"mdia", b"minf", b"stbl", b"edts", b"dinf", b"udta", b"moof", b"traf"}
FIELDS = "codec string, timescale bigint, duration bigint, frames bigint, keyframes array<struct<offset:bigint,length:bigint>>, payload binary"


def _box(kind: bytes, *body: bytes) -> bytes:
    size = 8 + sum(map(len, body))
    if size < 1 << 32:
        return struct.pack(">I4s", size, kind) + b"".join(body)
    return struct.pack(">I4sQ", 1, kind, size + 8) + b"".join(body)


def _full(kind: bytes, *body: bytes, flags: int = 0) -> bytes:
    return _box(kind, struct.pack(">I", flags), *body)


def padded(data: bytes) -> bytes:
    return data + PAD * (-len(data) % FRAME or (0 if data else FRAME))


def mux(payload: bytes) -> bytes:
    """A container around whole frames; the same payload always gives the same bytes."""
    frames = len(payload) // FRAME
    chunks = -(-frames // GROUP)
    matrix = struct.pack(">9i", 0x10000, 0, 0, 0, 0x10000, 0, 0, 0, 0x40000000)
    duration = frames * FRAME
    entry = _box(b"raw ", bytes(6), struct.pack(">HHHIHHHHI", 1, 0, 0, 0, 1, 8, 0, 0, RATE << 16))
    rows = [(1, GROUP, 1)] if chunks > 1 or frames == GROUP else []
    if frames % GROUP:
        rows.append((chunks, frames % GROUP, 1))
    tables = (
        _full(b"stsd", struct.pack(">I", 1), entry),
        _full(b"stts", struct.pack(">III", 1, frames, FRAME)),
        _full(b"stss", struct.pack(">I", chunks), (np.arange(chunks, dtype=">u4") * GROUP + 1).astype(">u4").tobytes()),
        _full(b"stsc", struct.pack(">I", len(rows)), b"".join(struct.pack(">III", *r) for r in rows)),
        _full(b"stsz", struct.pack(">II", FRAME, frames)),
    )
    file_type = _box(b"ftyp", b"isom", struct.pack(">I", 512), b"isommp42")
    wide = len(payload) > 1 << 31

    def movie(first: int) -> bytes:
        kind, code = (b"co64", ">u8") if wide else (b"stco", ">u4")
        offsets = (first + np.arange(chunks, dtype=np.int64) * GROUP * FRAME).astype(code).tobytes()
        table = _box(b"stbl", *tables, _full(kind, struct.pack(">I", chunks), offsets))
        data = _box(b"dinf", _full(b"dref", struct.pack(">I", 1), _full(b"url ", flags=1)))
        info = _box(b"minf", _full(b"smhd", bytes(4)), data, table)
        media = _box(
            b"mdia",
            _full(b"mdhd", struct.pack(">IIIIHH", 0, 0, RATE, duration & 0xFFFFFFFF, 0x55C4, 0)),
            _full(b"hdlr", struct.pack(">I4s12s", 0, b"soun", bytes(12)), b"bytes\0"),
            info,
        )
        head = _full(b"tkhd", struct.pack(">IIIII8sHHHH", 0, 0, 1, 0, duration & 0xFFFFFFFF, bytes(8), 0, 0, 0x100, 0), matrix, bytes(8), flags=7)
        top = _full(b"mvhd", struct.pack(">IIIIIH10s", 0, 0, RATE, duration & 0xFFFFFFFF, 0x10000, 0x100, bytes(10)), matrix, bytes(24), struct.pack(">I", 2))
        return _box(b"moov", top, _box(b"trak", head, media))

    lead = len(file_type) + len(movie(0)) + (16 if len(payload) + 8 >= 1 << 32 else 8)
    return file_type + movie(lead) + _box(b"mdat", payload)


def walk(data: memoryview, begin: int = 0, end: int | None = None, path: tuple[bytes, ...] = ()) -> Iterator[tuple[tuple[bytes, ...], int, int]]:
    """(path, body begin, body end) of every box, depth first. A box that does not fit its parent raises ValueError."""
    end = len(data) if end is None else end
    while begin < end:
        if begin + 8 > end:
            raise ValueError("a box is cut off")
        size, kind = struct.unpack_from(">I4s", data, begin)
        body = begin + 8
        if size == 1:
            size, body = struct.unpack_from(">Q", data, begin + 8)[0], begin + 16
        elif size == 0:
            size = end - begin
        stop = begin + size
        if stop > end or stop < body:
            raise ValueError("a box does not fit its parent")
        here = (*path, kind)
        yield here, body, stop
        if kind in CONTAINERS and len(here) < 16:
            yield from walk(data, body, stop, here)
        begin = stop


@dataclass(frozen=True)
class Track:
    codec: str
    timescale: int
    duration: int
    offsets: np.ndarray  # of each sample
    sizes: np.ndarray
    sync: np.ndarray  # sample numbers from 0


def _numbers(data: memoryview, at: int, end: int, width: int, code: str) -> np.ndarray:
    count = struct.unpack_from(">I", data, at + 4)[0]
    items = width * np.dtype(code).itemsize
    if at + 8 + count * items > end:
        raise ValueError("a table is cut off")
    return np.frombuffer(data, code, count * width, at + 8).astype(np.int64).reshape(count, width)


def tracks(data: bytes) -> list[Track]:
    view, found, boxes = memoryview(data), [], {}
    for path, begin, end in walk(view):
        if path == (b"moov", b"trak"):
            found.append(boxes := {})
        elif path[:2] == (b"moov", b"trak"):
            boxes[path[-1]] = (begin, end)
    return [_track(view, b) for b in found]


def _track(view: memoryview, boxes: dict[bytes, tuple[int, int]]) -> Track:
    begin, _ = boxes[b"mdhd"]
    timescale = struct.unpack_from(">I", view, begin + (20 if view[begin] == 1 else 12))[0]
    codec = bytes(view[boxes[b"stsd"][0] + 12 : boxes[b"stsd"][0] + 16]).decode("latin-1")
    stts = _numbers(view, *boxes[b"stts"], 2, ">u4")
    fixed, count = struct.unpack_from(">II", view, boxes[b"stsz"][0] + 4)
    sizes = np.full(count, fixed, np.int64) if fixed else _numbers(view, boxes[b"stsz"][0] + 4, boxes[b"stsz"][1], 1, ">u4").ravel()
    chunk = _numbers(view, *boxes[b"co64"], 1, ">u8").ravel() if b"co64" in boxes else _numbers(view, *boxes[b"stco"], 1, ">u4").ravel()
    stsc = _numbers(view, *boxes[b"stsc"], 3, ">u4")
    spans = np.diff(np.append(stsc[:, 0], len(chunk) + 1))
    per_chunk = np.repeat(stsc[:, 1], np.maximum(spans, 0))
    if len(per_chunk) != len(chunk) or per_chunk.sum() != count or stts[:, 0].sum() != count:
        raise ValueError("the sample tables disagree")
    of_chunk = np.repeat(np.arange(len(chunk)), per_chunk)
    before = np.cumsum(sizes) - sizes
    first = np.cumsum(per_chunk) - per_chunk
    offsets = chunk[of_chunk] + before - before[first[of_chunk]] if count else before
    if count and (int(offsets.min()) < 0 or int((offsets + sizes).max()) > len(view)):
        raise ValueError("a sample lies outside the file")
    sync = _numbers(view, *boxes[b"stss"], 1, ">u4").ravel() - 1 if b"stss" in boxes else np.arange(count)
    if len(sync) and (sync.min() < 0 or sync.max() >= count):
        raise ValueError("a key frame has no sample")
    return Track(codec, timescale, int((stts[:, 0] * stts[:, 1]).sum()), offsets, sizes, sync)


def payload(data: bytes, track: Track) -> bytes:
    """The samples' bytes in order; neighbours in the file are sliced at once."""
    if not len(track.offsets):
        return b""
    ends = track.offsets + track.sizes
    cut = np.flatnonzero(track.offsets[1:] != ends[:-1]) + 1
    begins = track.offsets[np.r_[0, cut]]
    stops = ends[np.r_[cut - 1, len(ends) - 1]]
    return b"".join([data[a:b] for a, b in zip(begins.tolist(), stops.tolist())])


def store(docs: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, media binary): each whole text's UTF-8 bytes as a container."""
    ship(docs.sparkSession)

    def run(batches):
        for batch in slices(batches, "text"):
            data = [text.encode() for text in batch.column("text").to_pylist()]
            media = [mux(padded(d)) for d in data]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(map(len, data), pa.int64()), pa.array(media, pa.binary())], ["doc_id", "n_bytes", "media"])

    return columns.documents(docs).mapInArrow(run, "doc_id bigint, n_bytes bigint, media binary")


def inspect(stored: DataFrame, media: str = "media") -> DataFrame:
    """``stored`` with the fields of each container's first track and its payload."""
    ship(stored.sparkSession)

    def look(data: bytes | None) -> tuple:
        try:
            track = tracks(data)[0]
            keys = [{"offset": o, "length": s} for o, s in zip(track.offsets[track.sync].tolist(), track.sizes[track.sync].tolist())]
            return track.codec, track.timescale, track.duration, len(track.offsets), keys, payload(data, track)
        except (TypeError, ValueError, KeyError, IndexError, OverflowError, struct.error):
            return (None,) * 6

    def run(batches):
        kinds = (pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.struct([("offset", pa.int64()), ("length", pa.int64())])), pa.binary())
        names = [f.split()[0] for f in FIELDS.split(", ")]
        for batch in slices(batches, media):
            rows = [look(data) for data in batch.column(media).to_pylist()]
            made = [pa.array(c, k) for c, k in zip(zip(*rows), kinds)]
            yield pa.RecordBatch.from_arrays([*batch.columns, *made], [*batch.schema.names, *names])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in stored.schema)
    return stored.mapInArrow(run, f"{schema}, {FIELDS}")


def round_trip(docs: DataFrame) -> DataFrame:
    """Store the texts in a table of media, then read what was stored."""
    return inspect(Staging(docs.sparkSession, "media").table(store(docs), "media"))


def feature(frame: DataFrame) -> DataFrame:
    """``frame`` with a ``feature`` string: codec, seconds, frames and the key frames' byte ranges."""
    ranges = F.array_join(F.transform("keyframes", lambda k: F.concat_ws("+", k["offset"].cast("string"), k["length"].cast("string"))), ",")
    return frame.withColumn(
        "feature",
        F.concat(F.lit("codec="), F.col("codec"), F.lit(";duration="), F.col("duration"), F.lit("/"), F.col("timescale"), F.lit(";frames="), F.col("frames"), F.lit(";keyframes="), ranges),
    )
