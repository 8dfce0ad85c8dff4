"""Substring dedup by de Bruijn compaction over word windows.

A window of WINDOW words is an edge of the de Bruijn graph of the corpus. Edges
meet in buckets by their hash, after each task has kept only the first
occurrence of each of its own, so an edge that a third of all documents share
reaches its bucket once per task. A bucket names, for every later occurrence,
the earliest one as its source. A Spark join brings these back to their
documents, where a nonbranching path, edges that follow each other while their
sources do as well, is compacted into one span with its source's coordinates;
all words of the spans are removed. A second join compares the words of every
span with those at its source before the result stands (``differing``);
``verified`` shows the same span by span.

Edges compare by 56 bits of a hash and log2(buckets) bits of another, and the
buckets grow with the data; should hashes of different words ever be equal, the
comparison finds it and other hashes are drawn.

Defined cases: a null text has no words; documents under WINDOW words keep all;
a null doc_id comes after all others; rows that share a doc_id, or have none, are
told apart by 64 hash bits of their texts and follow each other by these, and if
the texts are equal too, are the same place, neither being earlier; an empty table gives an empty result. A text is
never cut: very long ones only make their task's arrays longer. Extra columns
are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blobs import BASES, NULL, bucket_of, buckets_for, opened, places_opened, places_packed, rows, runs, spans_hashed, squeezed, sub_batches, texts_opened, texts_packed, word_hashes
from .common import discarded, words, written

WINDOW, HASH_BYTES, DRAWS = 20, 7, 4
#: Bytes of text taken together in one step of a task, and in one bucket.
STEP, EACH = 4 << 20, 8 << 20
KINDS = [("bucket", pa.int64()), ("kind", pa.int64()), ("data", pa.binary())]
SPAN = pa.struct([("start", pa.int64()), ("words", pa.int64()), ("source_doc", pa.int64()), ("source_row", pa.int64()), ("source_start", pa.int64()), ("digest", pa.binary())])
CUT = [("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept", pa.string()), ("spans", pa.list_(SPAN))]
CUT_SQL = "doc_id long, n_words long, n_removed long, kept string, spans array<struct<start: long, words: long, source_doc: long, source_row: long, source_start: long, digest: binary>>"
ASKED_SQL = "bucket long, source_doc long, source_row long, source_start long, words long, digest binary"
EDGES, LATER = 0, 1


def told_apart(docs: DataFrame) -> DataFrame:
    """doc_id, row, text: row is 0 where the doc_id alone names a text, and else a hash of the text."""
    content = F.xxhash64(F.coalesce("text", F.lit("")))
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    hashed = docs.where("doc_id is not null").select("doc_id", content.alias("row"))
    several = written(hashed.groupBy("doc_id").agg(F.min("row").alias("least"), F.max("row").alias("most")).where("least < most").select("doc_id", F.lit(True).alias("several")), "several")
    if several.isEmpty():
        return docs.select("doc_id", F.when(F.col("doc_id").isNull(), content).otherwise(0).alias("row"), "text")
    return docs.join(several, "doc_id", "left").select("doc_id", F.when(F.col("doc_id").isNull() | F.col("several"), content).otherwise(0).alias("row"), "text")


def row_batches(batch: pa.RecordBatch, most: int) -> Iterator[tuple[np.ndarray, np.ndarray, list[str | None]]]:
    """Ids (NULL for null), rows and texts, by ids and rows, about ``most`` bytes at a time."""
    ids = batch.column(0).fill_null(NULL).to_numpy(zero_copy_only=False).astype(np.int64)
    row = batch.column(1).to_numpy(zero_copy_only=False).astype(np.int64)
    for at, texts in sub_batches(pa.record_batch([pa.array(np.arange(batch.num_rows)), batch.column(2)], names=["at", "text"]), most):
        order = np.lexsort((row[at], ids[at]))
        yield ids[at][order], row[at][order], [texts[k] for k in order.tolist()]


def later_packed(ids: np.ndarray, row: np.ndarray, starts: np.ndarray, source: np.ndarray, source_row: np.ndarray, source_start: np.ndarray, buckets: int) -> Iterator[tuple[int, bytes]]:
    """Later occurrences by the bucket of their document."""
    bucket = bucket_of(ids + row, buckets)
    order = np.lexsort((starts, row, ids, bucket))
    bucket = bucket[order]
    for a, b in runs(bucket):
        some = order[a:b]
        yield int(bucket[a]), squeezed(*places_packed(ids[some], starts[some], row[some]), np.diff(source[some], prepend=0), np.diff(source_row[some], prepend=0), np.diff(source_start[some], prepend=0))


def edges(docs: DataFrame, buckets: int, window: int = WINDOW, draw: int = 0) -> DataFrame:
    """bucket, kind, data: first occurrences of each step by their hash, and later ones by their document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ids, row, texts in row_batches(batch, STEP):
                hashes, counts = word_hashes(texts, BASES[0] + 8 * draw)
                if len(hashes) < window:
                    continue
                last = np.repeat(np.cumsum(counts), counts)  # where the document of each word ends
                at = np.flatnonzero(np.arange(len(hashes)) + window <= last)
                if not len(at):
                    continue
                key = spans_hashed(hashes, at, at + window, BASES[1])
                deal = (spans_hashed(hashes, at, at + window, BASES[2]) % np.uint64(buckets)).astype(np.uint16 if buckets <= 1 << 16 else np.int64)
                doc = np.repeat(np.arange(len(ids)), counts)[at]
                place, own = ids[doc], row[doc]
                start = at - (last[at] - counts[doc])
                _, first, which = np.unique(key, return_index=True, return_inverse=True)
                mine = first[which]
                twin = (place[mine] == place) & (own[mine] == own) & (start[mine] == start)
                out: list[tuple[int, int, bytes]] = []
                again = np.flatnonzero(~twin)
                if len(again):
                    out += [(b, LATER, data) for b, data in later_packed(place[again], own[again], start[again], place[mine[again]], own[mine[again]], start[mine[again]], buckets)]
                kept = np.flatnonzero(twin)
                kept = kept[np.argsort(deal[kept], kind="stable")]
                for a, b in runs(deal[kept].astype(np.int64)):
                    some = kept[a:b]
                    head = squeezed(*places_packed(place[some], start[some], own[some]))
                    tail = np.ascontiguousarray(key[some].astype("<u8").view(np.uint8).reshape(-1, 8)[:, :HASH_BYTES]).tobytes()
                    out.append((int(deal[some[0]]), EDGES, len(tail).to_bytes(4, "little") + tail + head))
                yield from rows(KINDS, *map(list, zip(*out, strict=True))).to_batches()

    return docs.mapInArrow(run, "bucket long, kind long, data binary")


def sources(found: DataFrame, buckets: int) -> DataFrame:
    """bucket (of the document), data: later occurrences with the coordinates of an earlier one, the earliest across tasks."""

    def resolve(table: pa.Table) -> pa.Table:
        out = [(b, d) for b, k, d in zip(*(table.column(c).to_pylist() for c in ("bucket", "kind", "data")), strict=True) if k == LATER]
        keys, ids, own, starts = [], [], [], []
        for kind, data in zip(table.column("kind").to_pylist(), table.column("data"), strict=True):
            if kind != EDGES:
                continue
            data = data.as_py()
            size = int.from_bytes(data[:4], "little")
            wide = np.zeros((size // HASH_BYTES, 8), np.uint8)
            wide[:, :HASH_BYTES] = np.frombuffer(data, np.uint8, size, 4).reshape(-1, HASH_BYTES)
            keys.append(wide.view("<u8").reshape(-1))
            i, s, r = places_opened(*opened(data[4 + size :]))
            ids.append(i)
            own.append(r)
            starts.append(s)
        if keys:
            key, doc, row, start = map(np.concatenate, (keys, ids, own, starts))
            del keys, ids, own, starts
            order = np.argsort(key)
            same = np.diff(key[order]) == 0
            met = order[np.r_[False, same] | np.r_[same, False]]
            if len(met):
                met = met[np.lexsort((start[met], row[met], doc[met], key[met]))]
                new = np.r_[True, np.diff(key[met]) != 0]
                first = met[np.flatnonzero(new)][np.cumsum(new) - 1]
                late = (doc[met] != doc[first]) | (row[met] != row[first]) | (start[met] != start[first])
                met, first = met[late], first[late]
                if len(met):
                    out += later_packed(doc[met], row[met], start[met], doc[first], row[first], start[first], buckets)
        return rows([KINDS[0], KINDS[2]], [b for b, _ in out], [d for _, d in out])

    return found.repartition(buckets, "bucket").groupBy("bucket").applyInArrow(resolve, "bucket long, data binary")


def texts_by_bucket(docs: DataFrame, buckets: int) -> DataFrame:
    """bucket, data: whole texts with their ids, packed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ids, row, texts in row_batches(batch, 8 * STEP):
                bucket = bucket_of(ids + row, buckets)
                order = np.argsort(bucket, kind="stable")
                parts = [order[a:b] for a, b in runs(bucket[order])]
                yield from rows([KINDS[0], KINDS[2]], [int(bucket[p[0]]) for p in parts], [texts_packed(ids[p], [texts[k] for k in p.tolist()], row[p]) for p in parts]).to_batches()

    return docs.mapInArrow(run, "bucket long, data binary")


def paths(starts: np.ndarray, source: np.ndarray, source_row: np.ndarray, source_start: np.ndarray, window: int) -> list[dict]:
    """Nonbranching paths of the later edges of one document, in ascending order, as spans."""
    step = (np.diff(starts) == 1) & (np.diff(source) == 0) & (np.diff(source_row) == 0) & (np.diff(source_start) == 1)
    at = np.flatnonzero(np.r_[True, ~step])
    number = np.diff(np.r_[at, len(starts)])
    return [{"start": s, "words": n + window - 1, "source_doc": None if d == NULL else d, "source_row": r, "source_start": t} for s, n, d, r, t in zip(starts[at].tolist(), number.tolist(), source[at].tolist(), source_row[at].tolist(), source_start[at].tolist(), strict=True)]


def digest_of(listed: list[bytes]) -> bytes:
    return blake2b(b" ".join(listed), digest_size=16).digest()


def substring_dedup(docs: DataFrame, window: int = WINDOW, buckets: int | None = None) -> DataFrame:
    """doc_id, n_words, n_removed, kept (the words left, joined by a space) and spans (what was removed, and where it stood first).

    The result stands only when the words of every span equal those at its source;
    else all is done again with other hashes.
    """
    buckets = buckets or buckets_for(docs, EACH)
    docs = told_apart(docs)
    for draw in range(DRAWS):
        later = written(sources(edges(docs, buckets, window, draw), buckets), "later", "uncompressed")
        found = written(cut_out(docs, later, window, buckets), "cut")
        discarded(later)
        if not differing(found, docs, buckets).count():
            return found
        discarded(found)
    raise RuntimeError(f"words of spans and of their sources differ under {DRAWS} draws of hashes")


def cut_out(docs: DataFrame, later: DataFrame, window: int, buckets: int) -> DataFrame:
    """CUT of every row of docs (doc_id, row, text): what stays of it, and the spans of its later edges."""

    def cut(texts: pa.Table, later: pa.Table) -> pa.Table:
        parts = [opened(d.as_py()) for d in later.column("data")]
        if parts:
            ids, starts, row = (np.concatenate(x) for x in zip(*[places_opened(*p[:4]) for p in parts], strict=True))
            source, source_row, source_start = (np.concatenate([np.cumsum(p[k]) for p in parts]) for k in (4, 5, 6))
            order = np.lexsort((starts, row, ids))
            ids, row, starts, source, source_row, source_start = (x[order] for x in (ids, row, starts, source, source_row, source_start))
        else:
            ids = row = starts = source = source_row = source_start = np.zeros(0, np.int64)
        cuts = np.flatnonzero((np.diff(ids, prepend=~ids[:1]) != 0) | (np.diff(row, prepend=row[:1]) != 0)).tolist()
        places = {(int(ids[a]), int(row[a])): (a, b) for a, b in zip(cuts, [*cuts[1:], len(ids)], strict=False)}
        out: list[list] = [[] for _ in CUT]
        for data in texts.column("data"):
            some, raws, which = texts_opened(data.as_py())
            for doc_id, raw, r in zip(some.tolist(), raws, which.tolist(), strict=True):
                lo, hi = places.get((doc_id, r), (0, 0))
                listed, spans, n = raw.split(), [], 0
                size = len(listed)
                if hi > lo:
                    own = np.r_[True, np.diff(starts[lo:hi]) != 0]  # equal rows name a place twice
                    at = starts[lo:hi][own]
                    spans = paths(at, source[lo:hi][own], source_row[lo:hi][own], source_start[lo:hi][own], window)
                    cover = np.zeros(size + 1, np.int64)
                    np.add.at(cover, at, 1)
                    np.add.at(cover, at + window, -1)
                    for span in spans:
                        span["digest"] = digest_of(listed[span["start"] : span["start"] + span["words"]])
                    gone = np.cumsum(cover[:-1]) > 0
                    n = int(gone.sum())
                    listed = [w for w, g in zip(listed, gone.tolist(), strict=True) if not g]
                for column, value in zip(out, (None if doc_id == NULL else doc_id, size, n, b" ".join(listed).decode(), spans), strict=True):
                    column.append(value)
        return rows(CUT, *out)

    return texts_by_bucket(docs, buckets).groupBy("bucket").cogroup(later.groupBy("bucket")).applyInArrow(cut, CUT_SQL)


def differing(found: DataFrame, docs: DataFrame, buckets: int) -> DataFrame:
    """source_doc, source_start: where the words of a span differ from those at its source.

    Spans travel as digests of their words, equal ones of one source once, and the
    source's words are read where its whole text is: a hot source is asked few things.
    """

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            spans = pa.Table.from_batches([batch]).column(0).combine_chunks().flatten()
            columns = [spans.field(c) for c in ("source_doc", "source_row", "source_start", "words", "digest")]
            ids = columns[0].fill_null(NULL).to_numpy(zero_copy_only=False)
            bucket = bucket_of(ids + columns[1].to_numpy(zero_copy_only=False), buckets)
            yield pa.record_batch([pa.array(bucket), *columns], names=["bucket", "source_doc", "source_row", "source_start", "words", "digest"])

    def compare(texts: pa.Table, asked: pa.Table) -> pa.Table:
        wanted: dict[tuple, list[tuple]] = {}
        for d, r, *rest in zip(*(asked.column(c).to_pylist() for c in ("source_doc", "source_row", "source_start", "words", "digest")), strict=True):
            wanted.setdefault((NULL if d is None else d, r), []).append(tuple(rest))
        bad: list[tuple] = []
        for data in texts.column("data") if wanted else ():
            ids, raws, which = texts_opened(data.as_py())
            for doc_id, raw, r in zip(ids.tolist(), raws, which.tolist(), strict=True):
                asks = wanted.get((doc_id, r))
                if asks:
                    listed = raw.split()
                    bad += [(doc_id, s) for s, n, digest in asks if digest_of(listed[s : s + n]) != digest]
        return rows([("source_doc", pa.int64()), ("source_start", pa.int64())], [d for d, _ in bad], [s for _, s in bad])

    asked = found.select("spans").where(F.size("spans") > 0).mapInArrow(ask, ASKED_SQL).dropDuplicates()
    return texts_by_bucket(docs, buckets).groupBy("bucket").cogroup(asked.groupBy("bucket")).applyInArrow(compare, "source_doc long, source_start long")


def verified(found: DataFrame, docs: DataFrame) -> DataFrame:
    """doc_id, start, source_doc, source_start, words, same: each span beside the words at its source."""
    spans = found.select("doc_id", F.inline("spans"))
    texts = docs.select("doc_id", words(F.col("text")).alias("listed"))
    own = spans.join(texts, "doc_id").withColumn("own", F.slice("listed", F.col("start") + 1, F.col("words"))).drop("listed")
    there = own.join(texts.withColumnRenamed("doc_id", "source_doc"), "source_doc")
    return there.select("doc_id", "start", "source_doc", "source_start", "words", (F.col("own") == F.slice("listed", F.col("source_start") + 1, F.col("words"))).alias("same"))
