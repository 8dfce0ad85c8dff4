"""Hashing of points in Arrow batches, candidates of equal keys, and their verification."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.families import Batch, HashFamily, Name
from ..functions.metrics import Thresholds

DENSE = ("l1", "l2", "cosine")


def hashed(points: DataFrame, family: HashFamily, seed: int, names: Sequence[Name], k: int = 1) -> DataFrame:
    """id, keys: one key for each name. The feature is read once and stays behind."""
    names = list(names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = max(1, 2_000_000 // max(1, len(names) * k))
        for whole in batches:
            for at in range(0, whole.num_rows, step):
                batch = whole.slice(at, step)
                keys = family.keys(Batch(batch.column(1), family.kind), seed, names, k)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, keys.size + 1, len(names), dtype=np.int32)), pa.array(keys.reshape(-1)))
                yield pa.record_batch([batch.column(0), lists], names=["id", "keys"])

    return points.select("id", "feat").mapInArrow(run, "id long, keys array<long>")


def exploded(keys: DataFrame, *more: str) -> DataFrame:
    """id, tag, key: a row for each key; the tag is its place."""
    return keys.select("id", *more, F.posexplode("keys").alias("tag", "key"))


def chunked(rows: DataFrame, own: str, other: str, mine: str, theirs: str, chunk: int) -> DataFrame:
    """Each row with its chunk of its side of a bucket, once for every chunk of the other side.

    A bucket of n points has 2 * n / chunk chunks by a hash of the id, half full on
    average; the cells of its grid are separate groups of the join, whatever its size.
    """
    parts = lambda n: F.greatest(F.lit(1), F.ceil(F.when(F.col(n) > chunk, 2 * F.col(n) / chunk).otherwise(1))).cast("int")
    return rows.withColumn(mine, F.pmod(F.xxhash64("id", F.lit(17)), parts(own)).cast("int")).withColumn(theirs, F.explode(F.sequence(F.lit(0), parts(other) - 1)))


def met(left: DataFrame, right: DataFrame | None, by: list[str], chunk: int, carry: Sequence[str] = ()) -> DataFrame:
    """by, id_l, id_r and both sides' carried columns: pairs of the same bucket.

    Buckets without both sides go before anything is joined; large ones are
    dealt over the grid of their chunks.
    """
    if right is None:
        sizes = left.groupBy(*by).agg(F.count(F.lit(1)).alias("n_l")).where("n_l > 1").withColumn("n_r", F.col("n_l"))
        left = right = left.join(sizes, by)
        same = True
    else:
        sides = left.select(*by, F.lit(0).alias("side")).union(right.select(*by, F.lit(1).alias("side")))
        sizes = sides.groupBy(*by).agg(F.count_if(F.col("side") == 0).alias("n_l"), F.count_if(F.col("side") == 1).alias("n_r")).where("n_l > 0 and n_r > 0")
        left, right, same = left.join(sizes, by), right.join(sizes, by), False
    a = chunked(left, "n_l", "n_r", "chunk_l", "chunk_r", chunk).select(*by, "chunk_l", "chunk_r", F.col("id").alias("id_l"), *[F.col(c).alias(f"{c}_l") for c in carry])
    b = chunked(right, "n_r", "n_l", "chunk_r", "chunk_l", chunk).select(*by, "chunk_l", "chunk_r", F.col("id").alias("id_r"), *[F.col(c).alias(f"{c}_r") for c in carry])
    pairs = a.join(b, [*by, "chunk_l", "chunk_r"]).drop("chunk_l", "chunk_r")
    return pairs.where("id_l < id_r") if same else pairs


def measured(pairs: DataFrame, left: DataFrame, right: DataFrame | None, at: Thresholds) -> DataFrame:
    """pairs with ``value``, the distance or similarity. Features join by id only for what has met."""
    right = left if right is None else right
    both = pairs.join(left.select(F.col("id").alias("id_l"), F.col("feat").alias("feat_l")), "id_l").join(right.select(F.col("id").alias("id_r"), F.col("feat").alias("feat_r")), "id_r")
    names = pairs.columns
    if at.metric not in DENSE:
        return both.select(*names, at.measure(F.col("feat_l"), F.col("feat_r")).alias("value"))
    metric = at.metric

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            a, b = (batch.column(batch.schema.get_field_index(c)).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(n, -1 if n else 1) for c in ("feat_l", "feat_r"))
            yield pa.record_batch([*(batch.column(batch.schema.get_field_index(c)) for c in names), pa.array(dense(metric, a, b), from_pandas=True)], names=[*names, "value"])

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in pairs.schema)
    return both.mapInArrow(run, f"{schema}, value double")


def dense(metric: str, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    if metric == "l1":
        return np.abs(a - b).sum(axis=1)
    if metric == "l2":
        return np.sqrt(((a - b) ** 2).sum(axis=1))
    size = np.linalg.norm(a, axis=1) * np.linalg.norm(b, axis=1)
    with np.errstate(invalid="ignore", divide="ignore"):
        return np.where(size > 0, (a * b).sum(axis=1) / size, np.nan)


def near(pairs: DataFrame, at: Thresholds) -> DataFrame:
    """The near ones of measured pairs, with their distance to six digits."""
    return pairs.where(at.near(F.col("value"))).withColumn("dist", at.distance(F.col("value")))


def result(pairs: DataFrame) -> DataFrame:
    return pairs.select("id_l", "id_r", "dist")


def coin(seed: int, *columns: str | Column) -> Column:
    """A number in [0, 1) from the seed and the columns alone, so that retries agree."""
    bits = F.call_function("shiftrightunsigned", F.xxhash64(F.lit(seed), *[F.col(c) if isinstance(c, str) else c for c in columns]), F.lit(11))
    return bits / F.lit(float(1 << 53))
