"""The experiment workloads on the given tables: their points, thresholds, families and parameters."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from .functions.families import BitSampling, CauchyProjection, GaussianProjection, HashFamily, Hyperplane, MinHash
from .functions.metrics import Thresholds
from .sources.points import load_points
from .sources.scratch import written


@dataclass(frozen=True)
class Workload:
    """A named join: points (and those of the right side), thresholds, family, memory in points, and what makes its
    answer complete: rounds of the memory-aware join for each doubling of the points, where 3 give the guarantee for
    every pair at r, and repeats of the memory-oblivious join at log2(n) = 11, which grow as its power of 1.5."""

    left: str
    at: Thresholds
    family: HashFamily
    right: str | None = None
    memory: int = 125
    rounds: float = 0.27
    repeats: int = 4
    local_rows: int = 1

    def rounds_for(self, n: int) -> int:
        return max(1, math.ceil(self.rounds * math.log2(max(2, n))))

    def repeats_for(self, n: int) -> int:
        return max(1, math.ceil(self.repeats * (math.log2(max(2, n)) / 11) ** 1.5))

    def points(self, spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame | None]:
        """The features are written once: every later step reads id and feature only."""
        return written(load_points(spark, sf_dir, self.left), self.left), written(load_points(spark, sf_dir, self.right), self.right) if self.right else None


WORKLOADS = {
    "W1": Workload("doc_words", Thresholds("jaccard", 0.5, 0.1), MinHash()),
    "W1s": Workload("doc_shingles", Thresholds("jaccard", 0.5, 0.1), MinHash()),
    "W2": Workload("doc_signed256", Thresholds("cosine", 0.7, 0.2), Hyperplane(), rounds=0.45, repeats=5),
    "W3": Workload("doc_counts64", Thresholds("l1", 40, 80), CauchyProjection(160.0), rounds=0.72, repeats=16),
    "W3b": Workload("user_hist", Thresholds("l1", 20, 30), CauchyProjection(80.0), memory=75, rounds=1.45),
    "W4": Workload("emb", Thresholds("l2", 1.1, 1.2), GaussianProjection(2.2), memory=500, rounds=1.6),
    "W5": Workload("emb", Thresholds("cosine", 0.4, 0.2), Hyperplane(), memory=250, rounds=1.2),
    "W6": Workload("doc_finger64", Thresholds("hamming", 10, 20), BitSampling(64), rounds=0.45, repeats=8),
    "W6b": Workload("emb_sign", Thresholds("hamming", 16, 20), BitSampling(64), memory=250, rounds=1.2),
    "W7": Workload("bench_words", Thresholds("jaccard", 0.3, 0.1), MinHash(), right="doc_lines", memory=73, rounds=0.75, repeats=8),
    "W8": Workload("cust_brands", Thresholds("jaccard", 0.7, 0.5), MinHash(), memory=400, rounds=0.45),
    "W9": Workload("page_words", Thresholds("jaccard", 0.5, 0.2), MinHash(), memory=31, rounds=0.66),
    "W10": Workload("conv_words", Thresholds("jaccard", 0.2, 0.1), MinHash(), memory=268, rounds=1.19),
}
