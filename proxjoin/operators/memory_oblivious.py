"""The memory-oblivious join: recursive splitting by a primitive family, level by level.

All subproblems of a level, of all repetitions and repeats, are one frontier
frame (repeat, path, sub, side, id); a level is one plan and one written table,
so lineage and driver state stay small. Points of the smaller side that are
close to half of a sample of the larger one are joined with it at once and leave;
the others are hashed once for each child path. A subproblem ends at the last
level, when a side has at most one point, or when it fits one task anyway.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.families import Batch, HashFamily, Name, drawn
from ..functions.metrics import Thresholds
from ..plans.params import ObliviousPlan, memory_rows, plan_memory_oblivious, repeats_for_recall, repeats_whp
from ..sources.scratch import written
from .emission import MODES, distinct_pairs, thinned
from .hashing import coin, dense, measured, met, near, result

PROBLEM = ["repeat", "path", "sub"]
#: Points hashed in one step of a task; bytes of a frontier row in memory; points compared with a sample in one group.
STEP, ROW_BYTES, PART = 2048, 64, 4096


@dataclass
class Trace:
    """What a run has seen: sizes of subproblems and meetings of pairs by level."""

    plan: ObliviousPlan
    sizes: list[DataFrame] = field(default_factory=list)
    heavy: list[DataFrame] = field(default_factory=list)
    samples: list[DataFrame] = field(default_factory=list)
    meetings: DataFrame | None = None
    levels: int = 0


def initial(left: DataFrame, right: DataFrame | None, repeats: int) -> DataFrame:
    sides = left.select(F.lit(0).alias("side"), "id").union((left if right is None else right).select(F.lit(1).alias("side"), "id"))
    return sides.select(F.explode(F.sequence(F.lit(0), F.lit(repeats - 1))).alias("repeat"), F.lit(0).cast("long").alias("path"), F.lit(0).cast("long").alias("sub"), "side", "id")


def both_sides(frontier: DataFrame) -> DataFrame:
    """n_l, n_r of the subproblems that have points on both sides."""
    return frontier.groupBy(*PROBLEM).agg(F.count_if(F.col("side") == 0).alias("n_l"), F.count_if(F.col("side") == 1).alias("n_r")).where("n_l > 0 and n_r > 0")


def sample_larger(inner: DataFrame, size: int, seed: int) -> DataFrame:
    """PROBLEM, id: up to ``size`` points of each subproblem's larger side, by a seeded order.

    A first draw keeps three times as many in expectation, so the ranking sees a
    bounded part of a large side; where that draw falls short it is the sample.
    """
    larger = inner.where((F.col("side") == 1) == (F.col("n_l") <= F.col("n_r")))
    most = F.greatest("n_l", "n_r")
    drawn_ = larger.withColumn("draw", coin(seed, *PROBLEM, "id")).where((most <= 4 * size) | (F.col("draw") * most < 3 * size))
    ranked = drawn_.selectExpr(*PROBLEM, "id", f"row_number() over (partition by {', '.join(PROBLEM)} order by draw, id) as place")
    return ranked.where(F.col("place") <= size).drop("place")


def heavy_points(inner: DataFrame, sample: DataFrame, left: DataFrame, right: DataFrame, at: Thresholds) -> DataFrame:
    """PROBLEM, side, id: points of the smaller side within cr of at least half of the sample.

    A feature travels once for each subproblem, not for each pair: parts of PART
    points meet the whole sample of their subproblem in one group.
    """
    small = F.when(F.col("n_l") <= F.col("n_r"), 0).otherwise(1)
    number = F.ceil(F.least("n_l", "n_r") / F.lit(PART)).cast("int")
    feats = left.select(F.lit(0).alias("side"), "id", "feat").union(right.select(F.lit(1).alias("side"), "id", "feat"))
    mine = inner.where(F.col("side") == small).select(*PROBLEM, F.pmod(F.xxhash64("id", F.lit(23)), number).alias("part"), "side", "id").join(feats, ["side", "id"])
    parts = inner.select(*PROBLEM, (1 - small).alias("side"), F.explode(F.sequence(F.lit(0), number - 1)).alias("part")).distinct()
    theirs = sample.join(parts, PROBLEM).join(feats, ["side", "id"])
    kind = {"hamming": "bits", "jaccard": "sets"}.get(at.metric, "dense")

    def close(points: pa.Table, sample: pa.Table) -> pa.Table:
        if not (points.num_rows and sample.num_rows):
            return points.select([*PROBLEM, "side", "id"]).slice(0, 0)
        one, other = (Batch(t.column("feat").combine_chunks(), kind) for t in (points, sample))
        near = close_counts(at, one, other)
        return points.select([*PROBLEM, "side", "id"]).filter(pa.array(2 * near >= other.n))

    keys = [*PROBLEM, "part"]
    schema = ", ".join(f"{c} {t}" for c, t in inner.select(*PROBLEM).dtypes) + ", side int, id long"
    mine, theirs = (f.select(*[F.col(c).alias(c) for c in (*keys, "side", "id", "feat")]) for f in (mine, theirs))  # both descend from inner
    return mine.groupBy(*keys).cogroup(theirs.groupBy(*keys)).applyInArrow(close, schema)


def close_counts(at: Thresholds, points: Batch, sample: Batch) -> np.ndarray:
    """How many points of the sample are within cr of each point; both may be large, their product is never held."""
    total = np.zeros(points.n, np.int64)
    within = (lambda v: v >= at.cr) if at.similar else (lambda v: v <= at.cr)
    if points.kind == "sets":
        tokens, held = np.unique(sample.tokens, return_inverse=True)
        order = np.argsort(held, kind="stable")
        owner = np.repeat(np.arange(sample.n), np.diff(sample.starts))[order]
        begin = np.searchsorted(held[order], np.arange(len(tokens) + 1))
        sizes = np.diff(sample.starts)
        for k in range(points.n):
            own = points.tokens[points.starts[k] : points.starts[k + 1]]
            place = np.searchsorted(tokens, own)
            place = place[place < len(tokens)][tokens[place[place < len(tokens)]] == own[place < len(tokens)]]
            both = np.bincount(np.concatenate([owner[begin[t] : begin[t + 1]] for t in place.tolist()]), minlength=sample.n) if len(place) else np.zeros(sample.n, np.int64)
            either = len(own) + sizes - both
            total[k] = within(np.where(either == 0, 1.0, both / np.maximum(either, 1))).sum()
        return total
    for k in range(sample.n):
        value = np.bitwise_count(points.words ^ sample.words[k]) if points.kind == "bits" else dense(at.metric, points.matrix, sample.matrix[k : k + 1])
        total += within(value)
    return total


def name_of(level: int, repeat: int, path: int, j: int) -> Name:
    """The function of a child path; a path beyond 31 bits takes one number more."""
    return (level, repeat, path, j) if path < 1 << 31 else (level, repeat, path & 0x7FFFFFFF, j, path >> 31)


def split(inner: DataFrame, left: DataFrame, right: DataFrame | None, family: HashFamily, plan: ObliviousPlan, seed: int, level: int, how: str) -> DataFrame:
    """The next frontier: every point once for each child path, in the subproblem of its key there.

    A point's feature is read once, beside the list of the subproblems where it
    still is, and hashed by the functions of their children only: as many keys as
    frontier rows have children. Functions and the number of children, the last
    of which is drawn where 1 / p1 is no integer, follow from seed and path alone.
    """
    whole, most = math.floor(plan.branching + 1e-9), math.ceil(plan.branching - 1e-9)
    rest = 0.0 if how == "ceil" or whole == most else plan.branching - whole
    live = inner.groupBy("side", "id").agg(F.collect_list(F.struct("repeat", "path", "sub")).alias("live"))
    sides = [left, left if right is None else right]
    feats = sides[0].select(F.lit(0).alias("side"), "id", "feat").union(sides[1].select(F.lit(1).alias("side"), "id", "feat"))

    def keyed(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        points, lists = Batch(batch.column("feat"), family.kind), batch.column("live")
        problems = lists.flatten()
        repeat, path, sub = (problems.field(c).to_numpy(zero_copy_only=False) for c in ("repeat", "path", "sub"))
        point = np.repeat(np.arange(batch.num_rows), lists.value_lengths().to_numpy(zero_copy_only=False))
        order = np.lexsort((path, repeat))
        new = np.flatnonzero(np.r_[True, (np.diff(repeat[order]) != 0) | (np.diff(path[order]) != 0)])
        out: list[tuple[np.ndarray, ...]] = []
        for a, b in zip(new.tolist(), [*new[1:].tolist(), len(order)], strict=True):
            rows = order[a:b]
            r, p = int(repeat[rows[0]]), int(path[rows[0]])
            number = whole + int(drawn(seed, name_of(level, r, p, 77)).random() < rest) if rest else most
            if number:
                keys = family.keys(points.take(point[rows]), seed, [name_of(level, r, p, j) for j in range(number)], plan.k0)
                out.append((np.repeat(rows, number), np.tile(np.arange(number), len(rows)), keys.reshape(-1)))
        if out:
            rows, j, key = (np.concatenate(x) for x in zip(*out, strict=True))
            at = pa.array(point[rows])
            columns = [pa.array(repeat[rows], pa.int32()), pa.array(path[rows].astype(np.int64) * most + j), pa.array(sub[rows]), pa.array(j, pa.int64()), pa.array(key), batch.column("side").take(at), batch.column("id").take(at)]
            yield pa.record_batch(columns, names=["repeat", "path", "sub", "j", "key", "side", "id"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, STEP):
                if len(batch.slice(at, STEP)):
                    yield from keyed(pa.RecordBatch.from_arrays([c.combine_chunks() if isinstance(c, pa.ChunkedArray) else c for c in batch.slice(at, STEP).columns], names=batch.schema.names))

    rows = feats.join(live, ["side", "id"]).mapInArrow(run, "repeat int, path long, sub long, j long, key long, side int, id long")
    return rows.select("repeat", "path", F.xxhash64("sub", F.col("j").cast("int"), "key").alias("sub"), "side", "id")


def meetings(left: DataFrame, right: DataFrame | None, at: Thresholds, family: HashFamily, plan: ObliviousPlan, *, repeats: int, heavy: bool, local_rows: int, branching: str, seed: int, strict_leaf: bool, budget: float | None = None) -> Trace | None:
    """All meetings of pairs as repeat, level, path, sub, id_l, id_r, with the trace of sizes.

    A run whose ended subproblems hold more pairs than ``budget`` stops there, as None.
    """
    spent = 0
    other = left if right is None else right
    trace = Trace(plan)
    frontier, found = written(initial(left, right, repeats), "frontier"), []
    leaf_rows = 1 if strict_leaf else max(plan.sample, local_rows)
    chunk = max(2, leaf_rows, 4096)

    def pairs(a: DataFrame, b: DataFrame, level: int) -> DataFrame:
        got = met(a.select(*PROBLEM, "id"), b.select(*PROBLEM, "id"), PROBLEM, chunk)
        got = got.where("id_l < id_r") if right is None else got
        return got.select("repeat", F.lit(level).alias("level"), "path", "sub", "id_l", "id_r")

    for level in range(plan.depth + 1):
        sizes = written(both_sides(frontier).withColumn("level", F.lit(level)), "sizes")
        trace.sizes.append(sizes)
        trace.levels = level + 1
        last = F.lit(level == plan.depth) | (F.least("n_l", "n_r") <= 1) | (F.lit(not strict_leaf) & (F.greatest("n_l", "n_r") <= leaf_rows))
        whole = frontier.join(sizes.drop("level").withColumn("leaf", last), PROBLEM)
        leaf = whole.where("leaf")
        if budget:
            spent += sizes.where(last).agg(F.coalesce(F.sum(F.col("n_l") * F.col("n_r")), F.lit(0))).first()[0]
            if spent > budget:
                return None
        found.append(pairs(leaf.where("side = 0"), leaf.where("side = 1"), level))
        if sizes.where(~last).isEmpty():
            break
        inner = whole.where("not leaf")
        if heavy:
            sample = written(sample_larger(inner, plan.sample, seed + level), "sample")
            out = written(heavy_points(inner, sample, left, other, at), "heavy")
            trace.samples.append(sample.withColumn("level", F.lit(level)))
            trace.heavy.append(out.withColumn("level", F.lit(level)))
            rest = inner.join(out.select(*PROBLEM, F.col("side").alias("gone")).distinct(), PROBLEM)
            for side in (0, 1):
                mine = out.where(F.col("side") == side)
                theirs = rest.where((F.col("gone") == side) & (F.col("side") == 1 - side))
                found.append(pairs(mine, theirs, level) if side == 0 else pairs(theirs, mine, level))
            inner = inner.join(out, [*PROBLEM, "side", "id"], "left_anti")
        frontier = written(split(inner, left, right, family, plan, seed, level, branching), "frontier")
    trace.meetings = found[0]
    for more in found[1:]:
        trace.meetings = trace.meetings.union(more)
    return trace


def memory_oblivious_join(
    left: DataFrame,
    right: DataFrame | None,
    at: Thresholds,
    family: HashFamily,
    *,
    n: int | None = None,
    repeats: int | str | float = 1,
    max_depth: int | None = None,
    heavy: bool = True,
    local_rows: int | str = 1,
    branching: str = "random",
    dedup: str = "distinct",
    seed: int = 0,
    strict: bool = True,
    strict_leaf: bool = False,
    budget: float | None = None,
    tries: int = 3,
) -> DataFrame:
    """id_l, id_r, dist: the near pairs found.

    repeats is a number of independent runs, "whp" for the count that finds all
    pairs with high probability, or a recall below 1 that the runs shall reach at
    r. Under a budget of pairs looked at, instances with different seeds race: each
    stops at the level where it exceeds the budget, and the first to end within it
    is taken; the budget doubles after ``tries`` of them. local_rows="auto" ends
    subproblems that one task's memory holds.
    """
    if dedup not in MODES or dedup == "lookback":
        raise ValueError("dedup is none, distinct, random or random+distinct")
    if n is None:
        n = 2 * left.count() if right is None else left.count() + right.count()
    plan = plan_memory_oblivious(n, family, at.r, at.cr, strict, max_depth)
    if repeats == "whp":
        repeats = repeats_whp(n)
    elif isinstance(repeats, float) and repeats < 1:
        repeats = repeats_for_recall(plan.p1, plan.branching, plan.depth, repeats)
    rows = memory_rows(left.sparkSession, ROW_BYTES) if local_rows == "auto" else int(local_rows)
    run, attempt = None, 0
    while run is None:
        most = None if budget is None else budget * 2 ** (attempt // tries)
        run = meetings(left, right, at, family, plan, repeats=int(repeats), heavy=heavy, local_rows=rows, branching=branching, seed=seed + 101 * attempt, strict_leaf=strict_leaf, budget=most)
        attempt += 1
    if dedup == "distinct":
        return result(near(measured(run.meetings.select("id_l", "id_r").distinct(), left, right, at), at))
    found = near(measured(run.meetings, left, right, at), at)
    if dedup.startswith("random"):
        mean = float(math.ceil(plan.branching - 1e-9)) if branching == "ceil" else plan.branching
        p = F.pow(family.collision_column(F.col("value")), plan.k0)
        found = thinned(found, p, mean, F.col("level"), seed, "repeat", "path", "sub")
    return result(distinct_pairs(found) if dedup.endswith("distinct") else found)
