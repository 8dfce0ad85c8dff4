"""Best-fit packing of token sequences, certified by lower bounds.

Documents are encoded once; from then on only (doc_id, piece, length) travel.
Pieces are dealt evenly to partitions and each packs its own by best-fit
decreasing. Dual feasible functions give a lower bound on the bins that its
pieces need: a partition at its bound is certified and only its emptiest bin
can still be shared. The others have a gap and hand over every bin that isn't
full. What was handed over is dealt anew and packed again, until the total
meets the bound of all pieces, or an exchange takes less than a twentieth of the
gap away; one that makes it worse is undone.

Defined cases: a null text is the empty text, whose one token is the end id; a
null doc_id is kept as it is; rows that repeat a doc_id are packed each on its
own; a document longer than the limit is cut, a very long one gives many pieces;
an empty table gives an empty result. Extra columns are ignored.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blobs import by_bytes
from .common import written
from .encoding import encoder

LIMIT, END_ID = 4096, 1
#: Pieces in one packing task, bytes of text encoded together.
DEALT, STEP = 50_000, 4 << 20
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
PLACED = f"{PIECES}, sequence_id long, offset long, full boolean"


def pieces(docs: DataFrame, path: str, limit: int = LIMIT, end_id: int = END_ID) -> DataFrame:
    """The pieces of every document with their place, length and the CRC-32 of their ids."""
    schema = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64())])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tail = np.array([end_id], np.uint32)
        for part in (part for batch in batches for part in by_bytes(batch, STEP)):
            rows: list[tuple] = []
            for doc_id, ids in zip(part.column(0).to_pylist(), encoder(path).encode(part.column(1).to_pylist()), strict=True):
                ids = np.concatenate([ids, tail])
                for piece, at in enumerate(range(0, len(ids), limit)):
                    own = ids[at : at + limit]
                    rows.append((doc_id, piece, at, len(own), zlib.crc32(own.astype("<u4", copy=False))))
            yield pa.record_batch([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)] if rows else [pa.array([], f.type) for f in schema], schema=schema)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text")).mapInArrow(cut, PIECES)


def best_fit(lengths: np.ndarray, limit: int = LIMIT) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best-fit decreasing: the bin and offset of each piece, and how full each bin is."""
    bins, offsets, fills = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64), []
    room: list[int] = []  # the distinct gaps of open bins, ascending
    open_bins: dict[int, list[int]] = {}
    for i in np.argsort(-lengths, kind="stable").tolist():
        length = int(lengths[i])
        k = bisect_left(room, length)
        if k == len(room):
            b, gap = len(fills), limit
            fills.append(0)
        else:
            gap = room[k]
            b = open_bins[gap].pop()
            if not open_bins[gap]:
                del open_bins[gap], room[k]
        bins[i], offsets[i] = b, limit - gap
        fills[b] += length
        gap -= length
        if gap:
            if gap not in open_bins:
                open_bins[gap] = []
                insort(room, gap)
            open_bins[gap].append(b)
    return bins, offsets, np.array(fills, np.int64)


def fewest_bins(counts: np.ndarray, limit: int = LIMIT) -> int:
    """A lower bound on the bins for counts[x] pieces of length x, the best of two families of dual feasible functions.

    One takes pieces above limit - t as whole bins and drops those below t, for
    every t up to half; the other rounds (k + 1) * x / limit down, for small k.
    """
    if not counts.any():
        return 0
    x = np.arange(limit + 1)
    number, mass = np.r_[0, np.cumsum(counts)], np.r_[0, np.cumsum(counts * x)]
    t = np.arange(limit // 2 + 1)
    whole = number[limit + 1] - number[limit - t + 1]
    between = mass[limit - t + 1] - mass[t]
    best = int(np.max(-(-(whole * limit + between) // limit)))
    for k in range(1, 33):
        part, rest = np.divmod((k + 1) * x, limit)
        # in units of 1 / (k * limit), exact integers
        value = np.where(rest == 0, k * x, part * limit)
        best = max(best, int(-(-int((counts * value).sum()) // (k * limit))))
    return best


def packed(items: DataFrame, deal: int, limit: int, number: int) -> DataFrame:
    """items packed within each of ``deal`` even partitions; full tells that a bin is settled."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [b for b in batches if b.num_rows]
        if not parts:
            return
        table = pa.Table.from_batches(parts).combine_chunks()
        lengths = table.column("length").to_numpy()
        bins, offsets, fills = best_fit(lengths, limit)
        settled = fills == limit
        if len(fills) == fewest_bins(np.bincount(lengths, minlength=limit + 1), limit):
            settled = np.ones(len(fills), bool)
            settled[np.argmin(fills)] = fills.min() == limit
        here = (number << 56) + (TaskContext.get().partitionId() << 28)
        for name, values in (("sequence_id", bins + here), ("offset", offsets), ("full", settled[bins])):
            table = table.append_column(name, pa.array(values))
        yield from table.to_batches(max_chunksize=10_000)

    return items.repartition(deal).mapInArrow(pack, PLACED)


def bound(items: DataFrame, limit: int = LIMIT) -> int:
    """The lower bound for all pieces, from the counts of the at most ``limit`` lengths."""
    counts = np.zeros(limit + 1, np.int64)
    for length, n in items.groupBy("length").count().collect():
        counts[length] = n
    return fewest_bins(counts, limit)


def pack(docs: DataFrame, path: str, limit: int = LIMIT, end_id: int = END_ID, dealt: int = DEALT) -> DataFrame:
    """PIECES with sequence_id and offset, where each piece stands, and the bound on the number of
    sequences, beside which the number used shows the gap. Driver state is a few counts for each exchange."""
    cut = written(pieces(docs, path, limit, end_id), "pieces")
    least, settled, left, before = bound(cut, limit), [], cut, None
    closed = 0
    number = 0
    while True:  # each exchange but the last takes a twentieth of the gap away
        size = left.count()
        if not size and number:
            break
        deal = -(-size // dealt) or 1
        placed = written(packed(left, deal, limit, number), "packed")
        done, loose = placed.where("full"), placed.where("not full")
        open_bins, now = (f.select("sequence_id").distinct().count() for f in (loose, done))
        if before is not None and closed + now + open_bins > before[0]:  # the exchange made it worse: what was loose stays as it was
            settled.append(before[1])
            break
        closed += now
        if closed + open_bins <= least or not open_bins or deal == 1 or before is not None and 20 * (before[0] - closed - open_bins) < before[0] - least:
            settled.append(placed)
            break
        before = closed + open_bins, loose
        settled.append(done)
        left = loose.drop("sequence_id", "offset", "full")
        number += 1
    out = settled[0]
    for more in settled[1:]:
        out = out.union(more)
    return out.drop("full").withColumn("fewest_sequences", F.lit(least).cast("long"))
