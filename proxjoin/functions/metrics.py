"""Distances and similarities as columns, and the near, grey and far classes of a pair."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

SIMILARITIES = ("jaccard", "cosine")


def hamming(a: Column, b: Column) -> Column:
    return F.bit_count(a.bitwiseXOR(b)).cast("double")


def added(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda t, x: t + x)


def l1(a: Column, b: Column) -> Column:
    return added(F.zip_with(a, b, lambda x, y: F.abs(x.cast("double") - y.cast("double"))))


def l2(a: Column, b: Column) -> Column:
    gap = lambda x, y: x.cast("double") - y.cast("double")
    return F.sqrt(added(F.zip_with(a, b, lambda x, y: gap(x, y) * gap(x, y))))


def dot(a: Column, b: Column) -> Column:
    return added(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")))


def cosine(a: Column, b: Column) -> Column:
    """Null for a zero vector, so such a pair is never near."""
    size = F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))
    return F.when(size > 0, dot(a, b) / size)


def angle(a: Column, b: Column) -> Column:
    return F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), cosine(a, b))))


def jaccard(a: Column, b: Column) -> Column:
    """1 for two empty sets."""
    both = F.size(F.array_intersect(a, b))
    either = F.size(a) + F.size(b) - both
    return F.when(either == 0, F.lit(1.0)).otherwise(both / either)


MEASURES = {"hamming": hamming, "l1": l1, "l2": l2, "jaccard": jaccard, "cosine": cosine}


@dataclass(frozen=True)
class Thresholds:
    """r and cr of a metric; for similarities r is the larger one. Both are inclusive."""

    metric: str
    r: float
    cr: float

    def __post_init__(self):
        if self.metric not in MEASURES:
            raise ValueError(f"unknown metric {self.metric}")
        if (self.r <= self.cr) if self.similar else (self.r >= self.cr):
            raise ValueError("cr must be a weaker threshold than r")

    @property
    def similar(self) -> bool:
        return self.metric in SIMILARITIES

    def measure(self, a: Column, b: Column) -> Column:
        return MEASURES[self.metric](a, b)

    def near(self, value: Column) -> Column:
        return value >= self.r if self.similar else value <= self.r

    def close(self, value: Column) -> Column:
        """Within cr: near or grey."""
        return value >= self.cr if self.similar else value <= self.cr

    def classify(self, value: Column) -> Column:
        return F.when(self.near(value), "near").when(self.close(value), "grey").otherwise("far")

    def distance(self, value: Column) -> Column:
        """What results report: 1 less the similarity, or the distance, to six digits."""
        return F.round(1.0 - value if self.similar else value, 6) + 0.0  # no negative zero
