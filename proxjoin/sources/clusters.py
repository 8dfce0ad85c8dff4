"""Adversarial and synthetic point sets: a Python data source, and generators from ranges."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class ClusterSource(DataSource):
    """64-bit words around random centres: options points, clusters, flips, seed, partitions."""

    @classmethod
    def name(cls):
        return "hamming_clusters"

    def schema(self):
        return "id long, feat long, cluster int"

    def reader(self, schema):
        return ClusterReader(dict(self.options))


class ClusterReader(DataSourceReader):
    def __init__(self, options):
        self.points, self.clusters = int(options.get("points", 1000)), int(options.get("clusters", 10))
        self.flips, self.seed, self.parts = int(options.get("flips", 4)), int(options.get("seed", 0)), int(options.get("partitions", 4))

    def partitions(self):
        return [InputPartition(p) for p in range(self.parts)]

    def read(self, partition):
        centres = np.random.default_rng(self.seed).integers(-(1 << 63), 1 << 63, self.clusters)
        for i in range(partition.value, self.points, self.parts):
            rng = np.random.default_rng([self.seed, i])
            word = int(centres[i % self.clusters]) & (1 << 64) - 1
            for bit in rng.choice(64, self.flips, replace=False):
                word ^= 1 << int(bit)
            yield i, word - (1 << 64) if word >> 63 else word, i % self.clusters


def random_words(spark: SparkSession, n: int, seed: int = 0, first: int = 0) -> DataFrame:
    """Far from each other: uniform 64-bit words."""
    return spark.range(first, first + n).select("id", F.xxhash64(F.lit(seed), "id").alias("feat"))


def flipped(points: DataFrame, bits: int, shift: int) -> DataFrame:
    """A partner at Hamming distance exactly ``bits`` for each point, with its id shifted; which bits differ turns with the id."""
    mask, by = F.lit((1 << bits) - 1).cast("long"), (F.col("id") * 11 % 64).cast("int")
    turned = F.call_function("shiftleft", mask, by).bitwiseOR(F.call_function("shiftrightunsigned", mask, 64 - by))
    # a shift by 64 is none in Java, so an unturned mask stays what it is
    return points.select((F.col("id") + shift).alias("id"), F.col("feat").bitwiseXOR(turned).alias("feat"))


def two_cluster_points(spark: SparkSession, n: int) -> DataFrame:
    """Two tight clusters far apart: nearly all near pairs collide under every function."""
    word = F.when(F.col("id") % 2 == 0, F.lit(0)).otherwise(F.lit(-1)).cast("long")
    return spark.range(n).select("id", word.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("id") % 64).cast("int"))).alias("feat"))


def grey_ring_points(spark: SparkSession, r: int) -> DataFrame:
    """64 / (r // 2 + 1) words, each pair just beyond r: nothing is near, everything may be grey."""
    step = r // 2 + 1
    words = [((1 << step) - 1) << k * step for k in range(64 // step)]
    return spark.createDataFrame([(k, w - (1 << 64) if w >> 63 else w) for k, w in enumerate(words)], "id long, feat long")
