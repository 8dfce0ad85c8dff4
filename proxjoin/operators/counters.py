"""What runs are measured by: recall, collisions by class, level and size, replication, heavy points."""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..functions.metrics import Thresholds
from ..plans import costs
from .hashing import measured
from .memory_oblivious import PROBLEM, Trace


def recall(found: DataFrame, truth: DataFrame) -> DataFrame:
    """found, truth, both, recall, precision of two sets of pairs."""
    a = found.select("id_l", "id_r", F.lit(1).alias("f")).dropDuplicates(["id_l", "id_r"])
    b = truth.select("id_l", "id_r", F.lit(1).alias("t")).dropDuplicates(["id_l", "id_r"])
    both = a.join(b, ["id_l", "id_r"], "full")
    counts = both.agg(F.count("f").alias("found"), F.count("t").alias("truth"), F.count_if(F.col("f").isNotNull() & F.col("t").isNotNull()).alias("both"))
    share = lambda of: F.when(F.col(of) > 0, F.col("both") / F.col(of)).otherwise(F.lit(1.0))
    return counts.withColumn("recall", share("truth")).withColumn("precision", share("found"))


def collisions(meetings: DataFrame, left: DataFrame, right: DataFrame | None, at: Thresholds, *by: str) -> DataFrame:
    """by, near, grey, far: meetings of each class, repeated ones included."""
    classed = measured(meetings, left, right, at).withColumn("class", at.classify(F.col("value")))
    return classed.groupBy(*by).agg(*[F.count_if(F.col("class") == c).alias(c) for c in ("near", "grey", "far")])


def collisions_by_level(trace: Trace, left: DataFrame, right: DataFrame | None, at: Thresholds) -> DataFrame:
    return collisions(trace.meetings, left, right, at, "level")


def level_sizes(trace: Trace) -> DataFrame:
    out = trace.sizes[0]
    for more in trace.sizes[1:]:
        out = out.union(more)
    return out


def collisions_by_band(trace: Trace, left: DataFrame, right: DataFrame | None, at: Thresholds, memory: int) -> DataFrame:
    """level, band, far: by the power of two of the smaller side; everything from memory on is one band."""
    sizes = level_sizes(trace).withColumn("band", F.floor(F.log2(F.least(F.col("n_l"), F.col("n_r"), F.lit(memory)).cast("double"))).cast("int")).select(*PROBLEM, "level", "band")
    joined = trace.meetings.join(sizes, [*PROBLEM, "level"])
    return collisions(joined, left, right, at, "level", "band").select("level", "band", "far")


def replication_by_level(trace: Trace) -> DataFrame:
    """level, subproblems, rows: points of the frontier with their copies."""
    return level_sizes(trace).groupBy("level").agg(F.count(F.lit(1)).alias("subproblems"), F.sum(F.col("n_l") + F.col("n_r")).alias("rows"))


def expected_frame(trace: Trace, near: float, grey: float, far: float) -> DataFrame:
    """level and the most meetings of each class expected there, beside which observed ones stand."""
    spark = trace.meetings.sparkSession
    rows = [(level, *(float(v) for v in costs.expected_collisions(level, trace.plan.p1, trace.plan.p2, trace.plan.branching, near, grey, far).values())) for level in range(trace.plan.depth + 1)]
    return spark.createDataFrame(rows, "level int, near double, grey double, far double")


def oblivious_cost(trace: Trace, left: DataFrame, right: DataFrame | None, at: Thresholds, memories: list[int], block: float = 1) -> list[tuple[int, float]]:
    """Transfers for many memories from one run, since the run doesn't depend on memory: pairs are
    classed once and counted by level and power of two of the smaller side, at most 64 of them."""
    sizes = level_sizes(trace).select(*PROBLEM, "level", F.floor(F.log2(F.least("n_l", "n_r").cast("double"))).cast("int").alias("band"))
    seen = collisions(trace.meetings.join(sizes, [*PROBLEM, "level"]), left, right, at, "level", "band").collect()
    out = []
    for memory in memories:
        by_level: dict[int, float] = {}
        by_band: dict[tuple[int, int], float] = {}
        for r in seen:
            by_level[r.level] = by_level.get(r.level, 0.0) + r.near + r.grey
            band = (r.level, min(r.band, memory.bit_length() - 1))
            by_band[band] = by_band.get(band, 0.0) + r.far
        out.append((memory, costs.io_memory_oblivious(trace.plan.n, memory, block, trace.plan.p1, trace.plan.p2, by_level, by_band)))
    return out


def heavy_quality(trace: Trace, left: DataFrame, right: DataFrame | None, at: Thresholds) -> DataFrame:
    """level, side, id, share: for heavy points of the first level, how much of the other side is within cr."""
    other = left if right is None else right
    out: DataFrame | None = None
    for side, own, rest in ((0, left, other), (1, other, left)):
        heavy = trace.heavy[0].where(F.col("side") == side).select("level", "side", F.col("id").alias("id_l")).distinct()
        pairs = heavy.crossJoin(rest.select(F.col("id").alias("id_r")))
        share = measured(pairs, own, rest, at).groupBy("level", "side", F.col("id_l").alias("id")).agg(F.avg(F.when(at.close(F.col("value")), 1.0).otherwise(0.0)).alias("share"))
        out = share if out is None else out.union(share)
    return out


@dataclass
class Observed:
    rows: int
    seconds: float


def observe_run(df: DataFrame) -> Observed:
    """Runs a plan into nothing, counting rows as they pass; the plan stays the same."""
    seen = Observation("run")
    began = time.perf_counter()
    df.observe(seen, F.count(F.lit(1)).alias("rows")).write.format("noop").mode("overwrite").save()
    return Observed(seen.get["rows"], time.perf_counter() - began)
