"""Array operations on many texts at once, and the packed form in which rows of few bytes travel.

Words, windows and counts are too many to travel as rows. They are dealt into
numbered buckets, and what one task has for one bucket is one row with arrays
packed into bytes. Buckets grow in number with the data, so a bucket's content
is bounded by what one task of a thousandth or a millionth of the data holds.
"""

from __future__ import annotations

import struct
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Stands for a null id: it sorts last.
NULL = np.iinfo(np.int64).max
#: The hash of bytes is a polynomial in random values of them, modulo 2**64.
VALUES = np.random.default_rng(11).integers(0, 1 << 64, 256, np.uint64)
BASES = (0x9E3779B97F4A7C15, 0xD1342543DE82EF95, 0xAF251AF3B0F025B5)
#: Slots of tables of fixed size, as a power of two, and the blocks in which such a table travels.
SLOTS, BLOCKS = 22, 64
#: Bytes taken together by array operations.
CHUNK = 1 << 20
_powers: dict[tuple[int, bool], np.ndarray] = {}


def by_bytes(batch: pa.RecordBatch, step: int) -> Iterator[pa.RecordBatch]:
    """Parts of a batch, whose last column is the text, of about step bytes of text, or of one larger text."""
    first, size = 0, 0
    for k, n in enumerate(pa.compute.binary_length(batch.column(batch.num_columns - 1)).fill_null(0).to_pylist()):
        size += n
        if size >= step or k == batch.num_rows - 1:
            yield batch.slice(first, k + 1 - first)
            first, size = k + 1, 0


def powers(base: int, n: int, back: bool = False) -> np.ndarray:
    """base**1 .. base**n modulo 2**64, or their inverses."""
    known = _powers.get((base, back))
    if known is None or len(known) < n:
        known = np.cumprod(np.full(max(n, CHUNK + (CHUNK >> 3)), pow(base, -1, 1 << 64) if back else base, np.uint64), dtype=np.uint64)
        if n <= 1 << 24:
            _powers[base, back] = known
    return known[:n]


def mixed(x: np.ndarray) -> np.ndarray:
    """Each bit of the result depends on all bits: the finaliser of a public hash."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def spans_hashed(values: np.ndarray, at: np.ndarray, stop: np.ndarray, base: int) -> np.ndarray:
    """The hash of values[at:stop] for many spans at once, by prefix sums."""
    total = np.empty(len(values) + 1, np.uint64)
    total[0] = 0
    np.cumsum(values * powers(base, len(values)), out=total[1:])
    return mixed((total[stop] - total[at]) * powers(base, len(values) + 1, True)[at] + (stop - at).astype(np.uint64))


def located(raws: list[bytes], base: int = BASES[0]) -> tuple[bytes, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """All texts joined by line ends; where each word starts and stops in them, its hash, and how many words each text has.

    Bytes are taken CHUNK at a time, so that arrays of words are the largest.
    """
    found: list[tuple[np.ndarray, ...]] = []
    first, size, begin = 0, 0, 0
    for k, raw in enumerate(raws):
        size += len(raw) + 1
        if size < CHUNK and k < len(raws) - 1:
            continue
        some = raws[first : k + 1]
        b = np.frombuffer(b"\n".join(some) + b"\n", np.uint8)
        white = (b == 32) | ((b >= 9) & (b <= 13))
        edge = np.flatnonzero(np.diff(white, prepend=True))
        at, stop = edge[::2], edge[1::2]
        counts = np.diff(np.searchsorted(at, np.cumsum([len(r) + 1 for r in some])), prepend=0)
        found.append((at + begin, stop + begin, spans_hashed(VALUES[b], at, stop, base), counts))
        first, begin, size = k + 1, begin + len(b), 0
    none = np.zeros(0, np.int64)
    at, stop, key, counts = (np.concatenate(x) for x in zip(*found, strict=True)) if found else (none, none, none.astype(np.uint64), none)
    return b"\n".join(raws) + b"\n", at, stop, key, counts


def word_hashes(texts: list[str | None], base: int = BASES[0]) -> tuple[np.ndarray, np.ndarray]:
    """The hash of every word of all texts in a row, and how many words each text has."""
    return located([(t or "").encode() for t in texts], base)[3:]


def bucket_of(ids: np.ndarray, buckets: int) -> np.ndarray:
    return (mixed(ids.astype(np.int64).view(np.uint64)) % np.uint64(buckets)).astype(np.int64)


def buckets_for(docs: DataFrame, each: int, least: int = 16) -> int:
    """A power of two of buckets, for about ``each`` bytes of text in one."""
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = least
    while n * each < total:
        n *= 2
    return n


def sub_batches(batch: pa.RecordBatch, most: int) -> Iterator[tuple[np.ndarray, list[str | None]]]:
    """Ids (NULL for null) in ascending order with their texts, about ``most`` bytes at a time."""
    ids = batch.column(0).fill_null(NULL).to_numpy(zero_copy_only=False).astype(np.int64)
    first, texts, size = 0, [], 0
    for k in range(0, batch.num_rows, 64):  # only what is held becomes Python text
        some = batch.column(1).slice(k, 64).to_pylist()
        texts += some
        size += sum(len(t or "") for t in some)
        if size >= most or k + 64 >= batch.num_rows:
            order = np.argsort(ids[first : first + len(texts)], kind="stable")
            yield ids[first : first + len(texts)][order], [texts[j] for j in order.tolist()]
            first, texts, size = first + len(texts), [], 0


def squeezed(*arrays: np.ndarray, level: int = 1) -> bytes:
    """Arrays as bytes: like bytes of all numbers stand together, which packs small numbers well."""
    compress = zstandard.ZstdCompressor(level=level).compress
    out = [struct.pack("<I", len(arrays))]
    for a in arrays:
        data = compress(np.ascontiguousarray(a).view(np.uint8).reshape(len(a), a.itemsize).T.tobytes())
        out.append(struct.pack("<4sII", a.dtype.str[1:].encode(), len(a), len(data)) + data)
    return b"".join(out)


def opened(data: bytes) -> list[np.ndarray]:
    """The arrays that squeezed packed."""
    (n,) = struct.unpack_from("<I", data)
    at, out, expand = 4, [], zstandard.ZstdDecompressor().decompress
    for _ in range(n):
        kind, length, size = struct.unpack_from("<4sII", data, at)
        at += struct.calcsize("<4sII")
        dtype = np.dtype(f"<{kind.rstrip(b'\0').decode()}")
        flat = np.frombuffer(expand(data[at : at + size]), np.uint8) if length else np.zeros(0, np.uint8)
        out.append(np.ascontiguousarray(flat.reshape(dtype.itemsize, length).T).view(dtype).reshape(length))
        at += size
    return out


def places_packed(ids: np.ndarray, starts: np.ndarray, *more: np.ndarray) -> tuple[np.ndarray, ...]:
    """(id, more, start) by runs of ids and more as these, their counts, and steps of starts, which go back where a place comes twice."""
    new = np.diff(ids, prepend=~ids[:1]) != 0
    for m in more:
        new |= np.diff(m, prepend=m[:1]) != 0
    new = np.flatnonzero(new)
    steps = np.diff(starts, prepend=0)
    steps[new] = starts[new]
    return np.diff(ids[new], prepend=0), np.diff(np.r_[new, len(ids)]).astype("<u4"), steps.astype("<u4" if not len(steps) or steps.min() >= 0 else "<i8"), *(np.diff(m[new], prepend=0) for m in more)


def places_opened(ids: np.ndarray, counts: np.ndarray, steps: np.ndarray, *more: np.ndarray) -> tuple[np.ndarray, ...]:
    all_ids = np.repeat(np.cumsum(ids), counts)
    total = np.cumsum(steps, dtype=np.int64)
    first = np.cumsum(counts, dtype=np.int64) - counts
    before = np.where(first > 0, total[np.maximum(first, 1) - 1], 0) if len(first) else first
    return all_ids, total - np.repeat(before, counts), *(np.repeat(np.cumsum(m), counts) for m in more)


def runs(numbers: np.ndarray) -> list[tuple[int, int]]:
    """Where each run of equal numbers, none of them negative, begins and ends; none of an empty array."""
    cuts = np.flatnonzero(np.diff(numbers, prepend=-1)).tolist()
    return list(zip(cuts, [*cuts[1:], len(numbers)], strict=True)) if cuts else []


def rows(names_types: list[tuple[str, pa.DataType]], *columns: list) -> pa.Table:
    return pa.table([pa.array(c, t) for c, (_, t) in zip(columns, names_types, strict=True)], names=[n for n, _ in names_types])


def texts_packed(ids: np.ndarray, texts: list[str | None], *more: np.ndarray) -> bytes:
    raws = [(t or "").encode() for t in texts]
    body = zstandard.ZstdCompressor(level=3).compress(b"".join(raws))
    head = squeezed(np.asarray(ids, "<i8"), np.array([len(r) for r in raws], "<u4"), *more)
    return struct.pack("<I", len(head)) + head + body


def texts_opened(data: bytes) -> tuple:
    (size,) = struct.unpack_from("<I", data)
    ids, lengths, *more = opened(data[4 : 4 + size])
    body = zstandard.ZstdDecompressor().decompress(data[4 + size :])
    stops = np.cumsum(lengths, dtype=np.int64)
    return ids, [body[a:b] for a, b in zip((stops - lengths).tolist(), stops.tolist(), strict=True)], *more


def slots_counted(df: DataFrame, slots: Callable[[pa.RecordBatch], Iterator[np.ndarray]]) -> np.ndarray:
    """How often each of the 2**SLOTS slots comes among those of all batches: a table of fixed size, whatever df holds."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << SLOTS, np.uint32)
        for batch in batches:
            for some in slots(batch):
                np.add.at(total, some, np.uint32(1))
        yield pa.record_batch([pa.array(range(BLOCKS), pa.int64()), pa.array([squeezed(part) for part in total.reshape(BLOCKS, -1)], pa.binary())], names=["block", "data"])

    def add(table: pa.Table) -> pa.Table:
        total = np.zeros((1 << SLOTS) // BLOCKS, np.uint64)
        for data in table.column("data"):
            total += opened(data.as_py())[0]
        total = np.minimum(total, np.iinfo(np.uint32).max).astype(np.uint32)
        return rows([("block", pa.int64()), ("data", pa.binary())], [table.column("block")[0].as_py()], [squeezed(total)])

    found = df.mapInArrow(run, "block long, data binary").groupBy("block").applyInArrow(add, "block long, data binary").toArrow()
    counts = np.zeros((BLOCKS, (1 << SLOTS) // BLOCKS), np.uint32)
    for block, data in zip(found.column("block").to_pylist(), found.column("data"), strict=True):
        counts[block] = opened(data.as_py())[0]
    return counts.ravel()
