"""Features of points: token sets, shingles, hashed vectors, fingerprints and histograms.

Hashes are digits of MD5, so that any engine can repeat them. Sets are native
columns; vectors and fingerprints add up such hashes in Arrow batches.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def md5_number(text: Column, first: int = 1, digits: int = 15) -> Column:
    return F.conv(F.substring(F.md5(text), first, digits), 16, 10).cast("long")


def tokens(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit("[a-z0-9]+"), F.lit(0))


def word_set(text: Column) -> Column:
    """Sorted distinct hashes of the tokens, each of which is hashed once for a text."""
    return F.array_sort(F.array_distinct(F.transform(F.array_distinct(tokens(text)), lambda t: md5_number(t))))


def shingle_set(text: Column, n: int = 3) -> Column:
    """Sorted distinct hashes of n consecutive tokens; empty for shorter texts."""

    def shingles(t: Column) -> Column:
        return F.when(F.size(t) < n, F.array().cast("array<string>")).otherwise(F.transform(F.sequence(F.lit(1), F.size(t) - (n - 1)), lambda i: F.concat_ws(" ", F.slice(t, i, n))))

    listed = F.transform(F.array(tokens(text)), shingles)[0]
    return F.array_sort(F.array_distinct(F.transform(listed, lambda t: md5_number(t))))


def strip_html(html: Column) -> Column:
    bare = F.regexp_replace(html, r"(?is)<(script|style)\b.*?</\1>", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(bare, r"<[^>]*>", " "), r"\s+", " "))


def sign_bits(vector: Column) -> Column:
    """Bit i tells whether element i is positive, for up to 64 elements."""
    parts = F.transform(vector, lambda x, i: F.when(x > 0, F.call_function("shiftleft", F.lit(1).cast("long"), i)).otherwise(F.lit(0).cast("long")))
    return F.aggregate(parts, F.lit(0).cast("long"), lambda a, x: a.bitwiseOR(x))


def by_batch(rows: DataFrame, feature: str, make: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> DataFrame:
    """(id, an array of numbers) to (id, feat): make gets all numbers of a batch and where each row's start."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(1)
            offsets = lists.offsets.to_numpy() - lists.offsets[0].as_py() if len(lists) else np.zeros(1, np.int64)
            flat = lists.flatten().to_numpy(zero_copy_only=False)
            made = make(flat, offsets)
            out = pa.FixedSizeListArray.from_arrays(pa.array(made.reshape(-1)), made.shape[1]) if made.ndim == 2 else pa.array(made)
            out = out.cast(pa.list_(out.type.value_type)) if made.ndim == 2 else out
            yield pa.record_batch([batch.column(0), out], names=["id", "feat"])

    return rows.mapInArrow(run, f"id long, feat {feature}")


def counted(slots: np.ndarray, offsets: np.ndarray, dim: int, weights: np.ndarray | None = None) -> np.ndarray:
    row = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    return np.bincount(row * dim + slots, weights=weights, minlength=(len(offsets) - 1) * dim).reshape(-1, dim)


def signed_vectors(points: DataFrame, dim: int = 256) -> DataFrame:
    """Token sets as vectors: each token adds its sign to its slot."""
    return by_batch(points.select("id", "feat"), "array<double>", lambda h, o: counted(h % dim, o, dim, np.where((h // dim) % 2 == 1, 1.0, -1.0)))


def count_vectors(texts: DataFrame, dim: int = 64) -> DataFrame:
    """id, text to vectors of how many tokens fall into each slot."""
    slots = texts.select("id", F.transform(tokens(F.col("text")), lambda t: md5_number(t, 1, 8)).alias("h"))
    return by_batch(slots, "array<int>", lambda h, o: counted(h % dim, o, dim).astype(np.int32))


def fingerprints64(texts: DataFrame, step: int = 1 << 16) -> DataFrame:
    """id, text to 64 bits, each the majority of that bit over the hashes of distinct tokens."""

    def vote(h: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        high, low = h[0::2].astype(np.uint64), h[1::2].astype(np.uint64)
        word = high << np.uint64(32) | low
        which = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets) // 2)
        total = np.zeros((len(offsets) - 1, 64), np.int64)
        for at in range(0, len(word), step):  # 64 numbers for each token of a whole batch would fill memory
            bits = np.unpackbits(word[at : at + step].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(np.int64) * 2 - 1
            np.add.at(total, which[at : at + step], bits)
        return np.packbits((total > 0), axis=1, bitorder="little").view("<i8").reshape(-1)

    halves = F.flatten(F.transform(F.array_distinct(tokens(F.col("text"))), lambda t: F.array(md5_number(t, 1, 8), md5_number(t, 9, 8))))
    return by_batch(texts.select("id", halves.alias("h")), "long", vote)


def group_sets(rows: DataFrame, key: str, number: str) -> DataFrame:
    """One set of item numbers for each key; a set is as long as the item kinds of its key."""
    return rows.select(F.col(key).cast("long").alias("id"), F.col(number).alias("h")).distinct().groupBy("id").agg(F.array_sort(F.collect_list("h")).alias("feat"))


EVENT_TYPES = ("click", "error", "purchase", "signup", "view")


def user_histogram(events: DataFrame, kinds: tuple[str, ...]) -> DataFrame:
    """For each user the counts of events by kind and six-hour band of the day."""
    cells = [F.count_if((F.col("event_type") == k) & (F.floor(F.hour("ts") / 6) == b)).cast("int").alias(f"{k}_{b}") for k in kinds for b in range(4)]
    wide = events.groupBy(F.col("user_id").alias("id")).agg(*cells)
    return wide.select("id", F.array(*wide.columns[1:]).alias("feat"))
