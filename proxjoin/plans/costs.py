"""Costs in block transfers: of reading and sorting, of each join, and the parts of the bound."""

from __future__ import annotations

import math

#: Published results, for comparison: metric, thresholds, rho, near and close pairs a point, and transfers
#: of single-level hashing (a lower bound), nested loops and the memory-aware join. Fixed values.
PUBLISHED = (
    ("text", "jaccard", 0.5, 0.1, 0.30, 1.8e3, 16e3, 7.5e9, 8e9, 3.2e9),
    ("text", "cosine", 0.7, 0.2, 0.51, 1.6e3, 16e3, 212e9, 8e9, 6.6e9),
    ("digits", "l1", 3000.0, 6000.0, 0.50, 1.8, 42.0, 29e6, 60e6, 12e6),
)


def io_scan(n: float, block: float) -> float:
    return n / block


def io_sort(n: float, memory: float, block: float) -> float:
    return n / block * max(1.0, math.log(max(n / block, 2), max(memory / block, 2)))


def io_sort_shortcut(n: float, factor: float = 8) -> float:
    """Two passes that read and write 2n points, for blocks of one point."""
    return factor * n


def io_nested(n: float, memory: float, block: float = 1) -> float:
    """Both sides of size n."""
    return 2 * n + n * n / (memory * block)


def io_single_level(n: float, rho: float, sort_factor: float = 8) -> float:
    """A lower bound: sorting n^(1 + rho) entries."""
    return io_sort_shortcut(n ** (1 + rho), sort_factor)


def io_t1(n: float, memory: float, block: float, rho: float, near: float) -> float:
    return (n / memory) ** rho * (n / block + near / (memory * block))


def io_t2(memory: float, block: float, close: float) -> float:
    return close / (memory * block)


def t1_dominance(n: float, memory: float, block: float, rho: float, near: float, close: float) -> float:
    return io_t1(n, memory, block, rho, near) / io_t2(memory, block, close)


def io_memory_aware(n: float, memory: float, block: float, reps: float, rounds: float, near: float, grey: float, far: float) -> dict[str, float]:
    """The parts with their constants: sorting for each repetition, reading small buckets, and 2 / (memory * block)
    for each pair that large buckets generate."""
    parts = {"partition": rounds * reps * io_sort(n, memory, block), "small": rounds * reps * n / block, "pairs": 2 * (near + grey + far) / (memory * block)}
    return parts | {"total": sum(parts.values())}


def collision_bounds(n: float, memory: float, reps: float, near: float, close: float) -> dict[str, float]:
    """Most near collisions, grey collisions (with high probability) and far ones (with the cap) of all rounds."""
    log = math.log2(max(2, n))
    return {"near": 3 * reps * log * near, "grey": 6 * log * close, "far": 24 * n * reps * memory * log}


def expected_collisions(level: int, p1: float, p2: float, branching: float, near: float, grey: float, far: float) -> dict[str, float]:
    """Most pairs of each class expected at a level of the recursion."""
    return {"near": near * branching**level, "grey": grey, "far": far * (p2 / p1) ** level}


def expected_band(level: int, band: int, n: float, p1: float, p2: float) -> float:
    """Most far pairs expected at a level in subproblems whose smaller side has 2^band to 2^(band + 1) points."""
    return n * 2 ** (band + 1) * (p2 / p1) ** level


def crossover(n: float, memory: float, p2: float) -> int:
    """The level from which subproblems act as the buckets of the memory-aware join."""
    return max(0, math.ceil(math.log(max(1.0, n / memory)) / math.log(1 / p2) - 1e-12))


def io_memory_oblivious(n: float, memory: float, block: float, p1: float, p2: float, by_level: dict[int, float], by_band: dict[tuple[int, int], float]) -> float:
    """From one run's trace for any memory: near and close collisions by level, and far ones by level and size band."""
    branching, last = 1 / p1, crossover(n, memory, p2)
    total = n * branching**last / block
    total += sum(c for level, c in by_level.items() if level <= last) / (memory * block)
    total += sum(c * branching / (block * 2**band) for (level, band), c in by_band.items() if level >= last)
    return total


def level_equivalence(n: float, memory: float, p1: float, p2: float) -> dict[str, float]:
    level = crossover(n, memory, p2)
    return {"level": level, "far": p2**level, "far_target": memory / n, "near": p1**level, "near_target": (memory / n) ** (math.log(p1) / math.log(p2))}


def overheads(n: float, memory: float, block: float, rho: float) -> dict[str, float]:
    return {"ours": (n / memory) ** rho, "nested": n / memory, "single_level": (n / block) ** rho, "gain": (memory / block) ** rho}


def dedup_cost(mode: str, reps: float, near: float, replication: float, block: float) -> float:
    """Extra transfers of avoiding repeated pairs; looking back costs comparisons only, a factor of reps at worst."""
    return {"none": 0.0, "random": 0.0, "lookback": 0.0, "distinct": replication * near / block}[mode]


def lower_bound_report(n: float, memory: float, block: float, rho: float, near: float, close: float) -> dict[str, float]:
    """The informal argument for methods by signatures: examined pairs for each scan, repetitions, and both parts."""
    return {"pairs_per_scan": memory * n, "far_probability": memory / n, "near_probability": (memory / n) ** rho, "repetitions": (n / memory) ** rho, "t1": io_t1(n, memory, block, rho, near), "t2": io_t2(memory, block, close), "subquadratic": float(close <= memory * n)}


def branching_moments(p: float, p1: float, level: int) -> dict[str, float]:
    """Mean and variance of the subproblems that hold a pair at a level, by independent branching into 1 / p1 parts."""
    whole, rest = math.floor(1 / p1), 1 / p1 - math.floor(1 / p1)
    mean, var = p / p1, whole * p * (1 - p) + rest * p - (rest * p) ** 2
    spread = var * level if abs(mean - 1) < 1e-12 else var * mean ** (level - 1) * (mean**level - 1) / (mean - 1)
    return {"children": mean, "mean": mean**level, "variance": spread}
