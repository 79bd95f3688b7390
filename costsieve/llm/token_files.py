"""Token-id files: one id array per segment with Elias-Fano coded document boundaries.

A file is a Parquet container (so that any store Spark writes to will do, with its atomic commits), with one row per segment:

    part, segment        place in the global order
    first                ids of the same part before the segment
    docs, ids            numbers of documents and ids
    doc_ids              the documents' ids, little-endian 64-bit, and nulls as a bit set
    low, high, samples   Elias-Fano code of the docs+1 boundaries inside the segment: packed low halves, unary high halves, and the place of
                         every 256th set bit for constant-time selection
    width, tokens        the concatenated ids, little-endian, of 2 bytes each if all of the segment's fit and else of 4

Boundaries inside a segment are 32-bit at most, so no table of 64-bit offsets exists anywhere; a document's global start is its part's start (one
number per part) plus ``first`` plus a selection. Readers select the boundaries of the documents that they hand out, a block of them at a time (``read``) or one
by its place (``fetch``), and never unpack a whole file's.

Defined results: a null or empty text has the end id only; a null doc_id sorts first; rows that repeat a doc_id are documents of their own, ordered by
their texts; an empty table makes an empty file; other columns are ignored. A document of 2**29 ids or more, beyond what one binary value can hold, stops the job.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import columns
from .piece_bpe import slices
from .staging import Staging, ship

SEGMENT_IDS = 1 << 18  # a segment closes at the first document that reaches this many ids
SAMPLE = 256
FILE = (
    "part int, segment int, first bigint, docs int, ids bigint, doc_ids binary, null_ids binary, "
    "low_bits int, low binary, high binary, samples binary, width int, tokens binary"
)


class EliasFano:
    """A non-decreasing sequence of n numbers in about n * (2 + log2(largest / n)) bits."""

    def __init__(self, n: int, low_bits: int, low: bytes, high: bytes, samples: bytes):
        self.n, self.low_bits = n, low_bits
        self.low, self.high = np.frombuffer(low, np.uint8), np.frombuffer(high, np.uint8)
        self.samples = np.frombuffer(samples, "<u4")

    @classmethod
    def of(cls, values: np.ndarray) -> "EliasFano":
        n, largest = len(values), int(values[-1]) if len(values) else 0
        low_bits = max(0, (largest // max(n, 1)).bit_length() - 1)
        values = values.astype(np.uint64)
        shifts = np.arange(low_bits, dtype=np.uint64)
        low = np.packbits(((values[:, None] >> shifts) & np.uint64(1)).astype(np.uint8).ravel(), bitorder="little")
        ones = (values >> np.uint64(low_bits)).astype(np.int64) + np.arange(n)
        bits = np.zeros(int(ones[-1]) + 1 if n else 0, np.uint8)
        bits[ones] = 1
        high = np.packbits(bits, bitorder="little")
        return cls(n, low_bits, low.tobytes(), high.tobytes(), ones[::SAMPLE].astype("<u4").tobytes())

    def _lows(self, begin: int, end: int) -> np.ndarray:
        k = self.low_bits
        if not k:
            return np.zeros(end - begin, np.int64)
        from_bit, to_bit = begin * k, end * k
        bits = np.unpackbits(self.low[from_bit // 8 : -(-to_bit // 8)], bitorder="little")[from_bit % 8 : from_bit % 8 + to_bit - from_bit]
        return bits.reshape(-1, k).astype(np.int64) @ (np.int64(1) << np.arange(k, dtype=np.int64))

    def select(self, begin: int, end: int | None = None) -> np.ndarray:
        """Numbers ``begin`` to ``end`` (one, if no end is given): from the sample before the first, set bits are counted up to the sample after the last."""
        end = begin + 1 if end is None else end
        if not 0 <= begin < end <= self.n:
            raise IndexError(f"no numbers {begin} to {end} among {self.n}")
        at, seen = int(self.samples[begin // SAMPLE]), begin - begin % SAMPLE
        last = -(-end // SAMPLE)
        stop = int(self.samples[last]) if last < len(self.samples) else 8 * len(self.high)
        bits = np.unpackbits(self.high[at // 8 : -(-stop // 8)], bitorder="little")
        ones = np.flatnonzero(bits[at % 8 :])[begin - seen : end - seen] + at
        return ((ones - np.arange(begin, end)) << self.low_bits) + self._lows(begin, end)

    def nbytes(self) -> int:
        return self.low.nbytes + self.high.nbytes + self.samples.nbytes


def in_order(docs: DataFrame) -> DataFrame:
    """(doc_id, text) over range partitions in ascending order, ready to be encoded and written where they are.

    Texts are dealt out before they are encoded: range bounds are sampled from what is dealt out, and nothing should be encoded twice.
    """
    return columns.documents(docs).repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")


def write(coded: DataFrame, path: str, encoding=None) -> None:
    """Write (doc_id, ids binary), which must be ordered as ``in_order`` leaves it.

    With ``encoding``, work on batches as ``byte_tokens.encoding`` gives it, the rows are documents, and encoding and writing share a worker.
    """
    ship(coded.sparkSession)

    def run(batches):
        from pyspark import TaskContext

        part, segment, first = TaskContext.get().partitionId(), 0, 0
        docs: list[int | None] = []
        held: list[bytes] = []
        size = 0

        def close():
            nonlocal segment, first, docs, held, size
            bounds = EliasFano.of(np.cumsum([0, *[len(x) // 4 for x in held]]))
            numbers = np.array([0 if d is None else d for d in docs], "<i8").tobytes()
            nulls = np.packbits([d is None for d in docs]).tobytes()
            row = (part, segment, first, len(docs), size, numbers, nulls, bounds.low_bits, bounds.low.tobytes(), bounds.high.tobytes(), bounds.samples.tobytes(), *_narrow(b"".join(held)))
            kinds = (pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.int32(), *[pa.binary()] * 3, pa.int32(), pa.binary())
            names = [c.split()[0] for c in FILE.split(", ")]
            out = pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(row, kinds)], names)
            segment, first, docs, held, size = segment + 1, first + size, [], [], 0
            return out

        for batch in encoding(batches) if encoding else slices(batches, "ids"):
            for doc, ids in zip(batch.column("doc_id").to_pylist(), batch.column("ids").to_pylist()):
                if len(ids) >= 1 << 31:
                    raise ValueError("a document of 2**29 ids or more does not fit one value")
                docs.append(doc)
                held.append(ids)
                size += len(ids) // 4
                if size >= SEGMENT_IDS:
                    yield close()
        if docs:
            yield close()

    source = columns.documents(coded) if encoding else columns.pick(coded, doc_id="doc_id", ids="ids")
    source.mapInArrow(run, FILE).write.option("compression", "zstd").parquet(path)


class Segment:
    """One row of a file."""

    def __init__(self, row: dict):
        self.row, self.docs = row, row["docs"]
        self.bounds = EliasFano(self.docs + 1, row["low_bits"], row["low"], row["high"], row["samples"])
        self.nulls = np.unpackbits(np.frombuffer(row["null_ids"], np.uint8))[: self.docs].astype(bool)

    def documents(self, begin: int, end: int, base: int) -> pa.RecordBatch:
        """Documents ``begin`` to ``end``; ``base`` is the segment's global start."""
        bounds = self.bounds.select(begin, end + 1)
        numbers = pa.array(np.frombuffer(self.row["doc_ids"], "<i8")[begin:end], mask=self.nulls[begin:end])
        tokens = np.frombuffer(self.row["tokens"], f"<u{self.row['width']}")[bounds[0] : bounds[-1]].astype("<u4", copy=False)
        offsets = ((bounds - bounds[0]) * 4).astype(np.int32)  # below 2**31: a block closes before, see ``blocks``
        ids = pa.Array.from_buffers(pa.binary(), end - begin, [None, pa.py_buffer(offsets.tobytes()), pa.py_buffer(tokens.tobytes())])
        return pa.RecordBatch.from_arrays([numbers, pa.array(bounds[:-1] + base), ids], ["doc_id", "start", "ids"])

    def blocks(self):
        """Runs of documents between samples. All but a segment's last document have fewer than SEGMENT_IDS ids together, so only that one may be large: it is a block of its own."""
        last = self.docs - 1
        cuts = [*range(0, last, SAMPLE), last, self.docs]
        return zip(cuts, cuts[1:])


def _starts(segments: DataFrame) -> dict[int, int]:
    """Global start of each part."""
    sums = {r["part"]: r["n"] for r in segments.groupBy("part").agg(F.sum("ids").alias("n")).collect()}  # one number per task that wrote
    starts, total = {}, 0
    for part in sorted(sums):
        starts[part], total = total, total + sums[part]
    return starts


def read(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, ids binary) of every document in the files at ``path``."""
    ship(spark)
    segments = spark.read.schema(FILE).parquet(path)
    starts = _starts(segments)

    def run(batches):
        for batch in slices(batches, "tokens"):
            for row in batch.to_pylist():
                segment, base = Segment(row), starts[row["part"]] + row["first"]
                for begin, end in segment.blocks():
                    yield segment.documents(begin, end, base)

    return segments.mapInArrow(run, "doc_id bigint, start bigint, ids binary")


def fetch(spark: SparkSession, path: str, wanted: DataFrame) -> DataFrame:
    """(doc_id, start, ids) of documents by their place: ``wanted`` holds (part, segment, place). Segments that nobody asks for are not read past their keys."""
    ship(spark)
    segments = spark.read.schema(FILE).parquet(path)
    starts = _starts(segments)
    asked = wanted.groupBy("part", "segment").agg(F.sort_array(F.collect_set("place")).alias("places"))  # at most a segment's documents

    def run(batches):
        for batch in slices(batches, "tokens"):
            for row in batch.to_pylist():
                segment, base = Segment(row), starts[row["part"]] + row["first"]
                for place in row["places"]:
                    yield segment.documents(place, place + 1, base)

    return segments.join(asked, ["part", "segment"]).mapInArrow(run, "doc_id bigint, start bigint, ids binary")


def _narrow(tokens: bytes) -> tuple[int, bytes]:
    ids = np.frombuffer(tokens, "<u4")
    return (4, tokens) if len(ids) and ids.max() > 0xFFFF else (2, ids.astype("<u2").tobytes())


def round_trip(coded: DataFrame, path: str | None = None, encoding=None) -> DataFrame:
    """Write ordered ``coded`` to files, at ``path`` or in the shared folder, and read them back."""
    path = path or f"{Staging(coded.sparkSession, 'token-files').path}/files"
    write(coded, path, encoding)
    return read(coded.sparkSession, path)
