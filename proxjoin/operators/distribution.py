"""Distributions of pairwise distances: cumulative counts, join densities and growth exponents."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.metrics import Thresholds
from ..sources.scratch import written
from .baselines import all_values, shared_values
from .hashing import DENSE, coin, dense, measured, met


def sample_points(points: DataFrame, n: int, of: int, seed: int = 0) -> DataFrame:
    """About n of the points, by a hash of the id: a statistical sample of a stated size."""
    return points if of <= n else points.where(coin(seed, "id") < n / of)


def values(points: DataFrame, at: Thresholds) -> DataFrame:
    """id_l, id_r, value of pairs: sets that share a token by counting shared ones (thresholds above 0 need no
    others), dense vectors in Arrow batches over a grid of chunks, words as columns."""
    if at.metric == "jaccard":
        return shared_values(points)
    if at.metric not in DENSE:
        return all_values(points, None, at)
    return measured(met(points.select(F.lit(0).alias("all"), "id"), None, ["all"], 256).drop("all"), points, None, at)


def dense_counts(points: DataFrame, at: Thresholds, edges: list[float], chunk: int = 4096) -> DataFrame:
    """bin, n: pairs of dense vectors by the number of edges, strict to weak, that leave them out, from one.

    Vectors stand in cells of two chunks each and only counts leave a cell, so no pair is a row. Values come
    from one matrix product; those within 1e-6 of an edge are taken again, as the joins take them.
    """
    parts = max(1, -(-points.count() // chunk))
    part = F.pmod(F.xxhash64("id", F.lit(29)), F.lit(parts)).cast("int")
    placed = points.where("feat is not null").select("id", "feat", part.alias("part"), F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("other"))
    cells = placed.select((F.least("part", "other") * parts + F.greatest("part", "other")).alias("cell"), "part", "id", "feat")
    metric, ordered = at.metric, np.array(edges) * (-1 if at.similar else 1)

    def count(table: pa.Table) -> pa.Table:
        ids, own = table.column("id").to_numpy(), table.column("part").to_numpy()
        vectors = table.column("feat").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(ids), -1)
        one = own == own.min()
        a, b = np.flatnonzero(one), np.flatnonzero(~one)
        cell, alone = table.column("cell")[0].as_py(), not len(b)
        total = np.zeros(len(edges) + 1, np.int64)
        if alone and cell // parts != cell % parts:  # the other chunk is empty
            a = a[:0]
        b = a if alone else b
        square = (vectors**2).sum(axis=1)
        for k in range(0, len(a), 256):
            rows = a[k : k + 256]
            if metric == "l1":
                value = np.stack([np.abs(vectors[b] - vectors[i]).sum(axis=1) for i in rows])
            else:
                dots = vectors[rows] @ vectors[b].T
                with np.errstate(invalid="ignore", divide="ignore"):
                    value = np.sqrt(np.maximum(square[rows, None] + square[b] - 2 * dots, 0)) if metric == "l2" else dots / np.sqrt(square[rows, None] * square[b])
                x, y = np.nonzero(np.any([np.abs(value - t) < 1e-6 for t in edges], axis=0))
                value[x, y] = dense(metric, vectors[rows[x]], vectors[b[y]])
            wanted = ids[rows][:, None] < ids[b] if alone else np.ones(value.shape, bool)
            told = (-value if at.similar else value)[wanted]
            total += np.bincount(np.searchsorted(ordered, told[~np.isnan(told)]), minlength=len(total))
        return pa.table({"bin": pa.array(np.arange(1, len(edges) + 1)), "n": pa.array(total[:-1])})

    return cells.repartition(max(16, parts * (parts + 1) // 2), "cell").groupBy("cell").applyInArrow(count, "bin long, n long").groupBy("bin").agg(F.sum("n").alias("n"))


def pairwise_cdf(points: DataFrame, at: Thresholds, bins: list[float]) -> DataFrame:
    """threshold, pairs: how many pairs are within each threshold (similarities: at least it).

    Pairs are counted into bins before anything is sorted, so the running sum sees one row for each threshold.
    """
    edges = sorted(bins, reverse=at.similar)
    value = F.col("value")
    # edges go from strict to weak: as many as hold are the last ones
    held = sum(F.when((value >= t) if at.similar else (value <= t), 1).otherwise(0) for t in edges)
    first = F.when(held > 0, len(edges) + 1 - held)
    if at.metric in DENSE:
        counts = dense_counts(points, at, edges)
    else:
        counts = values(points, at).groupBy(first.alias("bin")).agg(F.count(F.lit(1)).alias("n"))  # a filter here would be pushed into the join, and measure each pair again
    spark = points.sparkSession
    grid = spark.createDataFrame([(k + 1, float(t)) for k, t in enumerate(edges)], "bin long, threshold double")
    running = Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
    return grid.join(counts, "bin", "left").select("threshold", F.sum(F.coalesce("n", F.lit(0))).over(running).alias("pairs"))


def sampled_cdf(points: DataFrame, at: Thresholds, bins: list[float], n: int, sample: int | None = 10_000, seed: int = 0) -> DataFrame:
    """pairwise_cdf from about ``sample`` of the n points: counts scale with the square of the sample's share."""
    if sample is None or n <= sample:
        return pairwise_cdf(points, at, bins)
    some = written(sample_points(points, sample, n, seed), "sampled")
    scale = (n / max(1, some.count())) ** 2
    return pairwise_cdf(some, at, bins).withColumn("pairs", F.round(F.col("pairs") * scale).cast("long"))


def growth_exponent(cdf: DataFrame, low: float, high: float) -> DataFrame:
    """exponent, fit: the slope of log pairs over log threshold, and the square of their correlation."""
    some = cdf.where((F.col("threshold") >= low) & (F.col("threshold") <= high) & (F.col("pairs") > 0)).select(F.log("pairs").alias("y"), F.log("threshold").alias("x"))
    return some.agg(F.round(F.regr_slope("y", "x"), 6).alias("exponent"), F.round(F.regr_r2("y", "x"), 6).alias("fit"))


def join_density(points: DataFrame, at: Thresholds, n: int, sample: int | None = None, seed: int = 0) -> DataFrame:
    """near_per_point, close_per_point; from a sample both counts scale with the square of its share."""
    some = points if sample is None else sample_points(points, sample, n, seed)
    m = n if sample is None else some.count()
    scale = (n / max(1, m)) ** 2 / n
    value = F.col("value")
    return values(some, at).agg((F.count_if(at.near(value)) * scale).alias("near_per_point"), (F.count_if(at.close(value)) * scale).alias("close_per_point"))
