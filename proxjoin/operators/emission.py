"""How often a pair is reported: looking back, distinct results, or a coin for each emission."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .hashing import coin

MODES = ("none", "lookback", "distinct", "random", "random+distinct")


def first_meeting(earlier_l: str = "earlier_l", earlier_r: str = "earlier_r") -> Column:
    """Whether a pair met under no earlier function of its round: compares the keys that both carry, newest first."""
    return ~F.exists(F.zip_with(F.reverse(earlier_l), F.reverse(earlier_r), lambda a, b: a == b), lambda x: x)


def keep_probability(collision: Column, branching: float, level: Column | int) -> Column:
    """1 / (p * L)^level, at most 1: one emission of each pair in expectation."""
    return F.least(F.lit(1.0), F.pow(collision * branching, -(F.lit(level) if isinstance(level, int) else level)))


def thinned(pairs: DataFrame, collision: Column, branching: float, level: Column | int, seed: int, *names: str) -> DataFrame:
    """Emissions that their coin keeps, without a shuffle."""
    return pairs.where(coin(seed, "id_l", "id_r", *names) < keep_probability(collision, branching, level))


def distinct_pairs(pairs: DataFrame) -> DataFrame:
    return pairs.dropDuplicates(["id_l", "id_r"])


def replication(emitted: DataFrame) -> DataFrame:
    """emissions, pairs, replication: how often a pair is reported on average."""
    return emitted.groupBy("id_l", "id_r").count().agg(F.sum("count").alias("emissions"), F.count(F.lit(1)).alias("pairs"), F.avg("count").alias("replication"))
