"""The joins to compare with: exact loops, single-level hashing, and filters on sets."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.families import HashFamily
from ..functions.metrics import Thresholds
from ..plans.params import key_length
from .cells import l1_halved
from .exact_sets import exact_set_join
from .hashing import measured, met, near, result
from .memory_aware import memory_aware_join


def _pair(left: DataFrame, right: DataFrame | None) -> tuple[DataFrame, DataFrame]:
    right = left if right is None else right
    return left.select(F.col("id").alias("id_l"), F.col("feat").alias("feat_l")), right.select(F.col("id").alias("id_r"), F.col("feat").alias("feat_r"))


def all_values(left: DataFrame, right: DataFrame | None, at: Thresholds) -> DataFrame:
    """id_l, id_r, value of all pairs: quadratic by definition, for ground truth on small inputs."""
    a, b = _pair(left, right)
    pairs = a.crossJoin(b)
    pairs = pairs.where("id_l < id_r") if right is None else pairs
    return pairs.select("id_l", "id_r", at.measure(F.col("feat_l"), F.col("feat_r")).alias("value"))


def exact_join(left: DataFrame, right: DataFrame | None, at: Thresholds) -> DataFrame:
    return result(near(all_values(left, right, at), at))


def join_sizes(left: DataFrame, right: DataFrame | None, at: Thresholds) -> DataFrame:
    """near, grey, far: how many pairs are in each class."""
    value = F.col("value")
    close = F.coalesce(at.close(value), F.lit(False))
    is_near = F.coalesce(at.near(value), F.lit(False))
    return all_values(left, right, at).agg(F.count_if(is_near).alias("near"), F.count_if(close & ~is_near).alias("grey"), F.count_if(~close).alias("far"))


def block_nested_join(left: DataFrame, right: DataFrame | None, at: Thresholds, memory: int) -> DataFrame:
    """Exact: both sides in chunks of half the memory, every chunk with every other, as one bucket's grid."""
    rows = lambda p: p.select(F.lit(0).alias("all"), "id")
    pairs = met(rows(left), None if right is None else rows(right), ["all"], max(1, memory // 2))
    return result(near(measured(pairs.drop("all"), left, right, at), at))


def recursive_nested_join(left: DataFrame, right: DataFrame | None, at: Thresholds, leaf: int) -> DataFrame:
    """Exact, without knowing the memory: both sides are halved until a quadrant has a leaf's size.

    The last levels of a self-join by l1 run inside the tasks, where features are at hand once for all their pairs.
    """
    if right is None and at.metric == "l1":
        return result(near(l1_halved(left, at, leaf), at))
    right_ = left if right is None else right
    depth = max(0, math.ceil(math.log2(max(1, max(left.count(), right_.count()) / leaf))))
    a, b = (p.select("id", F.xxhash64("id", F.lit(5)).alias("h")).withColumn("cell_l", F.lit(0).cast("long")).withColumn("cell_r", F.lit(0).cast("long")) for p in (left, right_))
    for level in range(depth):
        bit = F.call_function("shiftrightunsigned", F.col("h"), F.lit(level)).bitwiseAND(F.lit(1))
        half = F.explode(F.array(F.lit(0).cast("long"), F.lit(1).cast("long")))
        a = a.withColumn("cell_l", 2 * F.col("cell_l") + bit).withColumn("half", half).withColumn("cell_r", 2 * F.col("cell_r") + F.col("half")).drop("half")
        b = b.withColumn("cell_r", 2 * F.col("cell_r") + bit).withColumn("half", half).withColumn("cell_l", 2 * F.col("cell_l") + F.col("half")).drop("half")
    pairs = a.select("cell_l", "cell_r", F.col("id").alias("id_l")).join(b.select("cell_l", "cell_r", F.col("id").alias("id_r")), ["cell_l", "cell_r"]).select("id_l", "id_r")
    pairs = pairs.where("id_l < id_r") if right is None else pairs
    return result(near(measured(pairs, left, right, at), at))


def single_level_lsh_join(left: DataFrame, right: DataFrame | None, at: Thresholds, family: HashFamily, k: int | None = None, reps: int | None = None, n: int | None = None, target: float = 0.999, seed: int = 0) -> DataFrame:
    """Keys so long that about one far point meets a point, and as many tables as the target recall at r needs."""
    if n is None:
        n = 2 * left.count() if right is None else left.count() + right.count()
    p1, p2 = family.p1p2(at.r, at.cr)
    k = k or key_length(n, 1, p2)
    reps = reps or math.ceil(math.log(1 - target) / math.log(1 - p1**k))
    return memory_aware_join(left, right, at, max(2, n), family, n=n, rounds=1, reps=reps, k=k, seed=seed)


def prefix_filter_join(points: DataFrame, at: Thresholds) -> DataFrame:
    """Pairs that share one of their rarest tokens, as many as any set at least r similar must share one of."""
    return exact_set_join(points, at, "prefix")


def positional_filter_join(points: DataFrame, at: Thresholds) -> DataFrame:
    """Prefix candidates whose first shared token leaves enough tokens after it on both sides."""
    return exact_set_join(points, at, "positional")


def shared_values(points: DataFrame) -> DataFrame:
    """id_l, id_r, value: Jaccard similarities of all pairs that share a token, from counts of shared tokens alone."""
    rows = points.select("id", F.size("feat").alias("size"), F.explode("feat").alias("token"))
    a = rows.select("token", F.col("id").alias("id_l"), F.col("size").alias("size_l"))
    b = rows.select("token", F.col("id").alias("id_r"), F.col("size").alias("size_r"))
    shared = a.join(b, "token").where("id_l < id_r").groupBy("id_l", "id_r", "size_l", "size_r").agg(F.count(F.lit(1)).alias("both"))
    return shared.select("id_l", "id_r", (F.col("both") / (F.col("size_l") + F.col("size_r") - F.col("both"))).alias("value"))


def inverted_index_join(points: DataFrame, at: Thresholds) -> DataFrame:
    """Near pairs from shared tokens; r must be above 0, and empty sets have none to share."""
    return result(near(shared_values(points), at))


def length_filter_join(points: DataFrame, at: Thresholds) -> DataFrame:
    """Sets in bins of sizes a factor 1 / r apart meet those of their own and the next bin, if their sizes allow it."""
    step = math.log(1 / at.r)
    binned = points.where(F.size("feat") > 0).select("id", F.size("feat").alias("size"), F.floor(F.log(F.size("feat").cast("double")) / step + 1e-9).alias("bin"))
    a = binned.select(F.col("id").alias("a"), F.col("size").alias("size_a"), F.explode(F.array("bin", F.col("bin") + 1)).alias("bin"), F.col("bin").alias("bin_a"))
    b = binned.select(F.col("id").alias("b"), F.col("size").alias("size_b"), "bin")
    pairs = a.join(b, "bin").where((F.col("size_b") * at.r <= F.col("size_a") + 1e-9) & (F.col("size_a") * at.r <= F.col("size_b") + 1e-9))
    pairs = pairs.where((F.col("bin") > F.col("bin_a")) | (F.col("a") < F.col("b"))).select(F.least("a", "b").alias("id_l"), F.greatest("a", "b").alias("id_r")).distinct()
    return result(near(measured(pairs, points, None, at), at))


def spark_ml_lsh_join(points: DataFrame, at: Thresholds, tables: int = 8, seed: int = 0) -> DataFrame:
    """Spark's own single-level MinHash join, as a second opinion; token hashes become vector places."""
    from pyspark.ml.feature import MinHashLSH
    from pyspark.ml.functions import array_to_vector, vector_to_array  # noqa: F401
    from pyspark.ml.linalg import SparseVector, VectorUDT

    size = 1 << 20
    to_vector = F.udf(lambda tokens: SparseVector(size, sorted({t % size for t in tokens}), [1.0] * len({t % size for t in tokens})), VectorUDT())
    vectors = points.where(F.size("feat") > 0).select("id", to_vector("feat").alias("features"))
    model = MinHashLSH(inputCol="features", outputCol="hashes", numHashTables=tables, seed=seed).fit(vectors)
    joined = model.approxSimilarityJoin(vectors, vectors, 1 - at.r + 1e-9, "dist").where("datasetA.id < datasetB.id")
    return joined.select(F.col("datasetA.id").alias("id_l"), F.col("datasetB.id").alias("id_r"), F.round("dist", 6).alias("dist"))
