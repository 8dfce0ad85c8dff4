"""Token ids as one wavelet matrix per shard, written, and read back.

A shard's file holds, for each bit of an id from the highest, a plane with that
bit of every token, tokens ordered by the bits before; samples of the ones
before every 512th place give rank in constant time and select by halving. So a
file gives back any token, counts a token up to any place and finds its k-th
occurrence without being expanded. Documents go to shards in order of doc_id.

File layout, little-endian: magic, planes, documents and tokens as four 32-bit
numbers; then blocks, each a 32-bit size and zstd data: doc_ids (64 bits, null
flags first), lengths (32 bits), and for each plane its bits and its samples.

Defined cases: a null text is the empty text, whose only id is the end id; a
null doc_id comes first; rows that repeat a doc_id follow each other, by text;
a document longer than a shard has its own; an empty table gives no file and an
empty result. Extra columns are ignored.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import written
from .encoding import encoder

END_ID, SHARD_TOKENS, SAMPLE = 2, 1_000_000, 512
MAGIC = 0x31584D57
ONES = np.array([bin(i).count("1") for i in range(256)], np.uint8)


class WaveletMatrix:
    """The bit planes of a sequence of ids, with access, rank and select."""

    def __init__(self, planes: list[np.ndarray], samples: list[np.ndarray], n: int):
        self.planes, self.samples, self.n = planes, samples, n
        self.zeros = [n - int(s[-1]) for s in samples]

    @classmethod
    def build(cls, ids: np.ndarray, planes: int | None = None) -> WaveletMatrix:
        """As many planes as the largest id has bits, unless more are asked for."""
        needed = int(ids.max(initial=0)).bit_length() or 1
        planes = planes or needed
        if needed > planes:
            raise ValueError(f"{planes} planes are too few for ids of {needed} bits")
        now, kept, samples = np.asarray(ids, np.uint16 if planes <= 16 else np.uint32), [], []
        for level in range(planes - 1, -1, -1):
            bit = (now & now.dtype.type(1 << level)).astype(bool)
            plane = np.packbits(bit, bitorder="little")
            kept.append(plane)
            whole = np.zeros(-(-len(plane) // (SAMPLE // 8)) * (SAMPLE // 8), np.uint8)
            whole[: len(plane)] = ONES[plane]
            samples.append(np.r_[0, np.cumsum(whole.reshape(-1, SAMPLE // 8).sum(axis=1, dtype=np.int64))].astype("<u4"))
            now = np.concatenate([now[~bit], now[bit]])
        return cls(kept, samples, len(ids))

    def _bit(self, level: int, i: int) -> int:
        return int(self.planes[level][i >> 3]) >> (i & 7) & 1

    def _ones(self, level: int, i: int) -> int:
        """Ones before place i of a plane."""
        block, plane = i // SAMPLE, self.planes[level]
        first = block * (SAMPLE // 8)
        count = int(self.samples[level][block]) + int(ONES[plane[first : i >> 3]].sum())
        return count + (int(ONES[plane[i >> 3] & ((1 << (i & 7)) - 1)]) if i & 7 else 0)

    def access(self, i: int) -> int:
        """The id at place i."""
        value = 0
        for level in range(len(self.planes)):
            bit, ones = self._bit(level, i), self._ones(level, i)
            value = value << 1 | bit
            i = self.zeros[level] + ones if bit else i - ones
        return value

    def _range(self, value: int, end: int) -> tuple[int, int]:
        lo, hi = 0, end
        for level in range(len(self.planes)):
            a, b = self._ones(level, lo), self._ones(level, hi)
            lo, hi = (self.zeros[level] + a, self.zeros[level] + b) if value >> (len(self.planes) - 1 - level) & 1 else (lo - a, hi - b)
        return lo, hi

    def rank(self, value: int, end: int | None = None) -> int:
        """How often an id stands before a place, everywhere by default."""
        lo, hi = self._range(value, self.n if end is None else end)
        return hi - lo

    def select(self, value: int, k: int) -> int:
        """The place of the k-th occurrence of an id, from 0."""
        lo, hi = self._range(value, self.n)
        if not 0 <= k < hi - lo:
            raise IndexError(f"id {value} has {hi - lo} occurrences")
        at = lo + k
        for level in range(len(self.planes) - 1, -1, -1):
            one = value >> (len(self.planes) - 1 - level) & 1
            at = self._find(level, at - self.zeros[level] if one else at, one)
        return at

    def _find(self, level: int, k: int, one: int) -> int:
        """The place of the k-th one or zero of a plane."""
        lo, hi = 0, self.n
        while lo < hi:
            mid = (lo + hi) // 2
            ones = self._ones(level, mid + 1)
            if (ones if one else mid + 1 - ones) > k:
                hi = mid
            else:
                lo = mid + 1
        return lo

    def decode(self) -> np.ndarray:
        """All ids, by undoing the planes from the lowest on."""
        kind = np.uint16 if len(self.planes) <= 16 else np.uint32
        now = np.zeros(self.n, kind)
        for place, level in enumerate(range(len(self.planes) - 1, -1, -1)):
            bit = np.unpackbits(self.planes[level], count=self.n, bitorder="little").view(bool)
            out = np.empty(self.n, kind)
            zeros = self.zeros[level]
            out[~bit] = now[:zeros]
            out[bit] = now[zeros:] | kind(1 << place)
            now = out
        return now


def to_file(doc_ids: list[int | None], lengths: np.ndarray, matrix: WaveletMatrix) -> bytes:
    nulls = np.array([d is None for d in doc_ids], np.uint8)
    ids = np.array([d or 0 for d in doc_ids], "<i8")
    pack = zstandard.ZstdCompressor(level=1).compress
    blocks = [nulls.tobytes() + np.diff(ids, prepend=0).astype("<i8").tobytes(), lengths.astype("<u4").tobytes()]
    for plane, sample in zip(matrix.planes, matrix.samples, strict=True):
        blocks += [plane.tobytes(), np.diff(sample, prepend=0).astype("<u2").tobytes()]
    small = [pack(b) for b in blocks]
    return struct.pack("<4I", MAGIC, len(matrix.planes), len(doc_ids), matrix.n) + b"".join(struct.pack("<I", len(b)) + b for b in small)


def from_file(data: bytes) -> tuple[list[int | None], np.ndarray, WaveletMatrix]:
    magic, planes, docs, n = struct.unpack_from("<4I", data)
    if magic != MAGIC:
        raise ValueError("not a wavelet matrix file")
    at, blocks, unpack = 16, [], zstandard.ZstdDecompressor().decompress
    for _ in range(2 + 2 * planes):
        (size,) = struct.unpack_from("<I", data, at)
        blocks.append(unpack(data[at + 4 : at + 4 + size]))
        at += 4 + size
    ids = np.cumsum(np.frombuffer(blocks[0], "<i8", offset=docs)).tolist()
    doc_ids = [None if null else d for d, null in zip(ids, blocks[0][:docs], strict=True)]
    samples = [np.cumsum(np.frombuffer(b, "<u2"), dtype=np.int64) for b in blocks[3::2]]
    return doc_ids, np.frombuffer(blocks[1], "<u4"), WaveletMatrix([np.frombuffer(b, np.uint8) for b in blocks[2::2]], samples, n)


def write_shards(docs: DataFrame, path: str, end_id: int = END_ID, shard_tokens: int = SHARD_TOKENS) -> DataFrame:
    """shard, part, n_docs, n_tokens, file: the written table of shard files.

    A range partition of doc_id puts documents in order; a shard's number is its
    partition's with its place there, so shards are in order of doc_id as well.
    """

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, place, tail = TaskContext.get().partitionId(), 0, np.array([end_id], np.uint32)
        planes = max(encoder(path).largest, end_id).bit_length()
        kind = np.uint16 if planes <= 16 else np.uint32  # what is held until a shard is full
        doc_ids: list[int | None] = []
        held: list[np.ndarray] = []
        total = 0

        def shard() -> pa.RecordBatch:
            lengths = np.array([len(x) for x in held], np.int64)
            file = to_file(doc_ids, lengths, WaveletMatrix.build(np.concatenate(held), planes))
            row = [part << 32 | place, part, len(doc_ids), int(lengths.sum()), file]
            return pa.record_batch([pa.array([v]) for v in row], names=["shard", "part", "n_docs", "n_tokens", "file"])

        for batch in batches:
            for k in range(0, batch.num_rows, 3000):
                some = batch.slice(k, 3000)
                for doc_id, ids in zip(some.column(0).to_pylist(), encoder(path).encode(some.column(1).to_pylist()), strict=True):
                    tokens = np.concatenate([ids, tail]).astype(kind)
                    if held and total + len(tokens) > shard_tokens:
                        yield shard()
                        place, doc_ids, held, total = place + 1, [], [], 0
                    doc_ids.append(doc_id)
                    held.append(tokens)
                    total += len(tokens)
        if held:
            yield shard()

    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    return written(ordered.mapInArrow(build, "shard long, part long, n_docs long, n_tokens long, file binary"), "shards", "uncompressed")


def read_documents(shards: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for shard, file in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                doc_ids, lengths, matrix = from_file(file.as_py())
                ids = matrix.decode().astype("<u4")
                stops = np.cumsum(lengths, dtype=np.int64)
                starts = stops - lengths
                sums = [zlib.crc32(ids[a:b]) for a, b in zip(starts.tolist(), stops.tolist(), strict=True)]
                columns = [pa.array([shard] * len(doc_ids), pa.int64()), pa.array(doc_ids, pa.int64()), pa.array(starts), pa.array(lengths.astype(np.int64)), pa.array(sums, pa.int64())]
                yield pa.record_batch(columns, names=["shard", "doc_id", "within", "n_tokens", "ids_crc32"])

    sizes = shards.select("shard", "part", "n_tokens")
    parts = sizes.groupBy("part").agg(F.sum("n_tokens").alias("n"))
    none = F.lit(0).cast("long")
    earlier = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    parts = parts.select("part", F.coalesce(F.sum("n").over(earlier), none).alias("before"))
    within = Window.partitionBy("part").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.join(parts, "part").select("shard", (F.col("before") + F.coalesce(F.sum("n_tokens").over(within), none)).alias("first"))
    rows = shards.select("shard", "file").mapInArrow(read, "shard long, doc_id long, within long, n_tokens long, ids_crc32 long")
    return rows.join(starts, "shard").select("doc_id", (F.col("first") + F.col("within")).alias("start"), "n_tokens", "ids_crc32")


def occurrences(shards: DataFrame, token: int) -> DataFrame:
    """shard, place: where an id stands in each shard, found by rank and select alone."""

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for shard, file in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                matrix = from_file(file.as_py())[2]
                places = [matrix.select(token, k) for k in range(matrix.rank(token))]
                yield pa.record_batch([pa.array([shard] * len(places), pa.int64()), pa.array(places, pa.int64())], names=["shard", "place"])

    return shards.select("shard", "file").mapInArrow(find, "shard long, place long")
