"""The memory-aware join: one level of long keys, tuned so that buckets fit into memory.

Keys of k joined functions make a far pair collide with probability memory / n.
Each of ``rounds`` rounds has ``reps`` repetitions; all repetitions of all
rounds are hashed in one pass over the points and joined in one equi-join on
(repetition, key), ids only. Buckets above half the memory are dealt over the
grid of their chunks. Pairs that met are verified by their features, so every
reported pair is near.
"""

from __future__ import annotations

import logging

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.families import HashFamily
from ..functions.metrics import Thresholds
from ..plans.params import AwarePlan, check_preconditions, plan_memory_aware, rounds_for_recall
from ..sources.scratch import written
from .cells import near_met
from .emission import MODES, distinct_pairs, first_meeting, thinned
from .hashing import exploded, hashed, measured, met, near, result
from .set_meetings import near_met_capped, near_met_sets, near_met_until


LOG = logging.getLogger("proxjoin")


def names_of(plan: AwarePlan, rounds: range) -> list[tuple[int, int]]:
    return [(r, j) for r in rounds for j in range(plan.reps)]


def by_round(plan: AwarePlan) -> list[list[tuple[int, int]]]:
    return [names_of(plan, range(r, r + 1)) for r in range(plan.rounds)]


def buckets(points: DataFrame, family: HashFamily, plan: AwarePlan, seed: int, rounds: range, lookback: bool = False) -> DataFrame:
    """tag, key, id: a point's bucket in every repetition; with lookback also the keys of its round before."""
    keys = hashed(points, family, seed, names_of(plan, rounds), plan.k)
    if not lookback:
        return exploded(keys)
    rows = keys.select("id", "keys", F.posexplode("keys").alias("tag", "key"))
    first = F.floor(F.col("tag") / plan.reps).cast("int") * plan.reps
    return rows.select("id", "tag", "key", F.slice("keys", first + 1, F.col("tag") - first).alias("earlier"))


def candidates(left: DataFrame, right: DataFrame | None, family: HashFamily, plan: AwarePlan, seed: int, rounds: range | None = None, lookback: bool = False) -> DataFrame:
    """tag, key, id_l, id_r: every meeting of a pair."""
    rounds = range(plan.rounds) if rounds is None else rounds
    # written, since the sizes of buckets and both sides of the join read them
    rows = lambda p: None if p is None else written(buckets(p, family, plan, seed, rounds, lookback), "buckets")
    pairs = met(rows(left), rows(right), ["tag", "key"], plan.chunk, ["earlier"] if lookback else [])
    return pairs.where(first_meeting()).drop("earlier_l", "earlier_r") if lookback else pairs


def capped(left: DataFrame, right: DataFrame | None, at: Thresholds, family: HashFamily, plan: AwarePlan, seed: int, batch: int, far_cap: float) -> DataFrame:
    """Meetings of near pairs where a point leaves the rest of its round once it has met more than far_cap far points.

    Counters are applied between batches of repetitions, so the result depends on
    the seed alone, not on the order of tasks; grey pairs never count, and every
    round starts with all points.
    """
    found: list[DataFrame] = []
    for number in range(plan.rounds):
        out: DataFrame | None = None
        counts: DataFrame | None = None
        for first in range(0, plan.reps, batch):
            names = [(number, j) for j in range(first, min(first + batch, plan.reps))]

            def rows(points: DataFrame | None, side: int, names=names, out=out, first=first, number=number) -> DataFrame | None:
                if points is None:
                    return None
                here = points if out is None else points.join(out.where(F.col("side") == side).select("id"), "id", "left_anti")
                return exploded(hashed(here, family, seed, names, plan.k)).withColumn("tag", F.col("tag") + number * plan.reps + first)

            pairs = written(measured(met(rows(left, 0), rows(right, 1), ["tag", "key"], plan.chunk).drop("key"), left, right, at), "met")
            found.append(near(pairs, at))
            far = pairs.where(~at.close(F.col("value")))
            other = 0 if right is None else 1
            both = far.select(F.lit(0).alias("side"), F.col("id_l").alias("id")).union(far.select(F.lit(other).alias("side"), F.col("id_r").alias("id")))
            now = both.groupBy("side", "id").agg(F.count(F.lit(1)).alias("n"))
            counts = written(now if counts is None else counts.union(now).groupBy("side", "id").agg(F.sum("n").alias("n")), "counters")
            out = counts.where(F.col("n") > far_cap)
    whole = found[0]
    for more in found[1:]:
        whole = whole.union(more)
    return whole


def emissions(left: DataFrame, right: DataFrame | None, at: Thresholds, family: HashFamily, plan: AwarePlan, seed: int = 0, lookback: bool = False) -> DataFrame:
    """tag, id_l, id_r, dist: each near meeting, repeated ones included."""
    return near(measured(candidates(left, right, family, plan, seed, lookback=lookback).drop("key"), left, right, at), at)


def emissions_among(values: DataFrame, points: DataFrame, at: Thresholds, family: HashFamily, plan: AwarePlan, seed: int = 0) -> DataFrame:
    """tag, id_l, id_r, value, dist: the rows of ``emissions`` for the near pairs in values (id_l, id_r, value).

    A pair is emitted wherever its two keys agree, so with all near pairs at hand no other meeting
    needs a row: with a short key those grow with the square of the points.
    """
    keys = written(hashed(points, family, seed, names_of(plan, range(plan.rounds)), plan.k), "keys")
    both = values.join(keys.toDF("id_l", "keys_l"), "id_l").join(keys.toDF("id_r", "keys_r"), "id_r")
    tags = F.filter(F.transform(F.arrays_zip("keys_l", "keys_r"), lambda x, j: F.when(x["keys_l"] == x["keys_r"], j)), lambda j: j.isNotNull())
    return near(both.select(F.explode(tags).alias("tag"), "id_l", "id_r", "value"), at)


def meetings_by_tag(points: DataFrame, family: HashFamily, plan: AwarePlan, seed: int = 0) -> DataFrame:
    """tag, meetings: how many pairs meet in each repetition, from the sizes of its buckets alone."""
    sizes = exploded(hashed(points, family, seed, names_of(plan, range(plan.rounds)), plan.k)).groupBy("tag", "key").agg(F.count(F.lit(1)).alias("n"))
    return sizes.groupBy("tag").agg(F.sum(F.expr("n * (n - 1) div 2")).alias("meetings"))


def points_of(left: DataFrame, right: DataFrame | None) -> int:
    return 2 * left.count() if right is None else left.count() + right.count()


def join_until_recall(left: DataFrame, right: DataFrame | None, at: Thresholds, memory: int, family: HashFamily, target: float = 0.999, *, n: int | None = None, seed: int = 0, cells: bool = False) -> DataFrame:
    """id_l, id_r, dist: rounds go on until the pairs found are ``target`` of all near pairs, by an estimate.

    A pair that collides with probability p has been found after so many functions
    with probability 1 - (1 - p)^functions, so each found pair stands for the inverse
    of that many. Without a pair at r found, as many rounds run as one there needs.
    Each round hashes anew and looks only at pairs that no earlier one has verified.
    cells are those of ``memory_aware_join``, for a self-join of sets.
    """
    n = points_of(left, right) if n is None else n
    plan = plan_memory_aware(n, memory, family, at.r, at.cr)
    if cells:
        if right is not None or family.kind != "sets":
            raise ValueError("cells are for a self-join of sets")

        def enough(functions: int, values: DataFrame, copies: int) -> bool:
            missed = F.pow(1 - F.pow(family.collision_column(F.col("value")), plan.k), functions)
            got, whole = values.agg(F.coalesce(F.sum("weight"), F.lit(0)), F.coalesce(F.sum(F.col("weight") / (1 - missed)), F.lit(0.0))).first()
            got, whole = got + copies, whole + copies
            return bool(got and got >= target * whole or not got and functions // plan.reps >= rounds_for_recall(plan.p1, plan.reps, target))

        values = near_met_until(left, at, family, seed, by_round(plan), plan.k, enough)
        if values is not None:
            return result(near(values, at))
    seen = found = None
    for number in range(plan.rounds):
        new = candidates(left, right, family, plan, seed, range(number, number + 1)).select("id_l", "id_r").distinct()
        new = new if seen is None else new.join(seen, ["id_l", "id_r"], "left_anti")
        now = written(measured(new, left, right, at), "round")
        seen = now.select("id_l", "id_r") if seen is None else seen.union(now.select("id_l", "id_r"))
        found = near(now, at) if found is None else found.union(near(now, at))
        missed = F.pow(1 - F.pow(family.collision_column(F.col("value")), plan.k), plan.reps * (number + 1))
        got, whole = found.agg(F.count(F.lit(1)), F.sum(1 / (1 - missed))).first()
        if got and got >= target * whole or not got and number + 1 >= rounds_for_recall(plan.p1, plan.reps, target):
            break
    return result(found)


def memory_aware_join(
    left: DataFrame,
    right: DataFrame | None,
    at: Thresholds,
    memory: int,
    family: HashFamily,
    *,
    n: int | None = None,
    rounds: int | None = None,
    reps: int | None = None,
    k: int | None = None,
    cap: str = "off",
    far_cap: float | None = None,
    batch: int = 4,
    dedup: str = "distinct",
    emission_reps: float | None = None,
    seed: int = 0,
    cells: bool = False,
) -> DataFrame:
    """id_l, id_r, dist: the near pairs found; right=None joins left with itself, id_l < id_r.

    rounds=None takes the count that finds all pairs with high probability,
    rounds=1 finds each with probability over one half. cap is off or round_batch.
    With cells, which needs a self-join of words, vectors or sets without emissions, and without a cap but for sets,
    the same buckets are looked through in cells of chunks of points, or for sets in groups of repetitions, so that
    no row is made for each key or meeting. Sets whose ids repeat take the plain way.
    """
    if dedup not in MODES:
        raise ValueError(f"dedup is one of {MODES}")
    if dedup == "lookback" and cap != "off":
        raise ValueError("with a far cap a point may leave before a pair meets, so looking back can't tell first meetings")
    if n is None:
        n = points_of(left, right)
    plan = plan_memory_aware(n, memory, family, at.r, at.cr, rounds, reps, k)
    for text in check_preconditions(n, memory, 1, plan.p1, plan.p2):
        LOG.info(text)
    if cells:
        if right is not None or dedup != "distinct" or cap != "off" and family.kind != "sets":
            raise ValueError("cells are for distinct pairs of a self-join, and of sets if there is a cap")
        names = names_of(plan, range(plan.rounds))
        if family.kind != "sets":
            return result(near(near_met(left, at, family, seed, names, plan.k), at))
        if cap == "off":
            values = near_met_sets(left, at, family, seed, names, plan.k, plan.reps)
        else:
            values = near_met_capped(left, at, family, seed, by_round(plan), plan.k, batch, plan.far_cap if far_cap is None else far_cap)
        if values is not None:
            return result(near(values, at))
    if cap == "round_batch":
        found = capped(left, right, at, family, plan, seed, batch, plan.far_cap if far_cap is None else far_cap)
    elif cap != "off":
        raise ValueError("cap is off or round_batch")
    elif dedup == "distinct":
        # a pair's features are fetched once, however often it met
        met_once = candidates(left, right, family, plan, seed).select("id_l", "id_r").distinct()
        return result(near(measured(met_once, left, right, at), at))
    else:
        found = emissions(left, right, at, family, plan, seed, lookback=dedup == "lookback")
    if dedup.startswith("random"):
        p = F.pow(family.collision_column(F.col("value")), plan.k)
        found = thinned(found, p, emission_reps or plan.reps, 1, seed, "tag")
    if dedup.endswith("distinct") or dedup == "lookback" and plan.rounds > 1:
        found = distinct_pairs(found)
    return result(found)
