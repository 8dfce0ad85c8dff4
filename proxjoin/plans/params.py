"""Parameters of the joins: key lengths, repetitions, depths, and the recall that they promise."""

from __future__ import annotations

import math
from dataclasses import dataclass

from ..functions.families import HashFamily


def rho(p1: float, p2: float) -> float:
    return math.log(p1) / math.log(p2)


def key_length(n: int, memory: int, p2: float) -> int:
    """The least number of joined functions that makes far pairs collide with probability memory / n."""
    if memory >= n:
        return 1
    return max(1, math.ceil(math.log(memory / n) / math.log(p2) - 1e-12))


@dataclass(frozen=True)
class AwarePlan:
    """Of the memory-aware join: n points, memory in points, key length, repetitions, rounds, chunk and far cap."""

    n: int
    memory: int
    k: int
    reps: int
    rounds: int
    chunk: int
    far_cap: int
    p1: float
    p2: float


def plan_memory_aware(n: int, memory: int, family: HashFamily, r: float, cr: float, rounds: int | None = None, reps: int | None = None, k: int | None = None) -> AwarePlan:
    p1, p2 = family.p1p2(r, cr)
    if not 0 < p2 < p1 <= 1:
        raise ValueError(f"the family doesn't tell r from cr: p1={p1:.3f}, p2={p2:.3f}")
    k = k or key_length(n, memory, p2)
    reps = reps or math.ceil(2 / p1**k)
    rounds = rounds or max(1, math.ceil(3 * math.log2(max(2, n))))
    return AwarePlan(n, memory, k, reps, rounds, max(1, memory // 2), 8 * reps * memory, p1**k, p2**k)


@dataclass(frozen=True)
class ObliviousPlan:
    """Of the memory-oblivious join: functions joined so that p1 is below one half, branching, depth and sample."""

    n: int
    k0: int
    branching: float
    depth: int
    sample: int
    p1: float
    p2: float


def plan_memory_oblivious(n: int, family: HashFamily, r: float, cr: float, strict: bool = True, max_depth: int | None = None) -> ObliviousPlan:
    p1, p2 = family.p1p2(r, cr)
    if not 0 < p2 < p1 <= 1:
        raise ValueError(f"the family doesn't tell r from cr: p1={p1:.3f}, p2={p2:.3f}")
    k0 = 1
    while strict and p1**k0 >= 0.5 and p1 < 1:
        k0 += 1
    p1, p2 = p1**k0, p2**k0
    depth = math.ceil(math.log(max(2, n)) / math.log(1 / p2) - 1e-12)
    return ObliviousPlan(n, k0, 1 / p1, depth if max_depth is None else min(depth, max_depth), math.ceil(18 * math.log2(max(2, n))), p1, p2)


def predicted_recall(p: float, branching: float, depth: int) -> float:
    """The probability that a pair with collision probability p meets in a subproblem of the last level."""
    s = 1.0
    whole, rest = math.floor(branching), branching - math.floor(branching)
    for _ in range(depth):
        miss = (1 - p * s) ** whole * (1 - rest * p * s)
        s = 1 - miss
    return s


def repeats_for_recall(p: float, branching: float, depth: int, target: float) -> int:
    s = predicted_recall(p, branching, depth)
    return 1 if s >= target else math.ceil(math.log(1 - target) / math.log(1 - s))


def aware_recall(p: float, reps: int, rounds: int = 1) -> float:
    """Without the far cap: the probability that a pair collides at least once; p is for whole keys."""
    return 1 - (1 - p) ** (reps * rounds)


def rounds_for_recall(p: float, reps: int, target: float) -> int:
    one = aware_recall(p, reps)
    return 1 if one >= target else math.ceil(math.log(1 - target) / math.log(1 - one))


def repeats_whp(n: int) -> int:
    return math.ceil(math.log2(max(2, n)) ** 1.5)


def tune_width(family: type, r: float, cr: float, low: float = 0.2, high: float = 0.95, steps: int = 60) -> HashFamily:
    """The projection whose width has the smallest rho among those with p1 between low and high."""
    found = []
    for j in range(steps):
        f = family(r * 2 ** (-2 + 7 * j / (steps - 1)))
        p1, p2 = f.p1p2(r, cr)
        if low <= p1 <= high and 0 < p2 < p1:
            found.append((rho(p1, p2), f.width, f))
    return min(found)[2]


def check_preconditions(n: int, memory: int, block: int, p1: float, p2: float) -> list[str]:
    """What a run violates of the assumptions behind the bounds."""
    out = []
    if memory < 18 * math.log2(max(2, n)) + 3 * block:
        out.append("memory holds fewer points than the sample and three blocks")
    if not p2 < p1 < 0.5:
        out.append("p2 < p1 < 1/2 does not hold; join functions until it does")
    if memory >= n:
        out.append("the input fits into memory")
    return out


def memory_rows(spark, row_bytes: int) -> int:
    """Points of a size that one task can hold, from the executors' memory."""
    text = spark.conf.get("spark.executor.memory", "1g").lower()
    unit = {"k": 1 << 10, "m": 1 << 20, "g": 1 << 30, "t": 1 << 40}.get(text[-1], 1)
    total = float(text.rstrip("kmgtb")) * unit
    cores = int(spark.conf.get("spark.executor.cores", "1"))
    return max(2, int(total * 0.3 / cores / max(1, row_bytes)))
