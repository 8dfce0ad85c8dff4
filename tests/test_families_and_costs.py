"""Families against their collision probabilities, parameters and costs against published numbers."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from proxjoin.functions import families
from proxjoin.functions.families import Batch, BitSampling, CauchyProjection, CustomFamily, GaussianProjection, Hyperplane, MinHash, normal_cdf
from proxjoin.plans import costs, params


def rate(family, a, b, n=4000):
    kind = pa.array([a, b], pa.int64()) if family.kind == "bits" else pa.array([a, b], pa.list_(pa.int64() if family.kind == "sets" else pa.float64()))
    v = family.primitive(Batch(kind, family.kind), 3, [(0, j) for j in range(n)])
    return (v[0] == v[1]).mean()


@pytest.mark.parametrize(
    "family,a,b,measure",
    [
        (BitSampling(64), 0, 0b1111_1111, 8),
        (MinHash(), list(range(30)), list(range(15, 45)), 15 / 45),
        (Hyperplane(), [1.0, 0.0], [math.cos(1.0), math.sin(1.0)], math.cos(1.0)),
        (CauchyProjection(4.0), [0.0, 0.0, 0.0], [1.0, 2.0, 0.0], 3.0),
        (GaussianProjection(2.0), [0.0, 0.0], [1.0, 1.0], math.sqrt(2)),
    ],
)
def test_collisions_follow_the_probability(family, a, b, measure):
    p = family.collision(measure)
    assert abs(rate(family, a, b) - p) < 4 * math.sqrt(p * (1 - p) / 4000)


def test_probability_columns_agree(spark):
    rows = spark.createDataFrame([(x / 10,) for x in range(1, 60)], "x double")
    for family in (BitSampling(64), CauchyProjection(4.0), GaussianProjection(2.0)):
        for r in rows.select("x", family.collision_column(F.col("x")).alias("p")).collect():
            assert r.p == pytest.approx(family.collision(r.x), abs=2e-6)
    for r in rows.where("x <= 1").select("x", Hyperplane().collision_column(F.col("x")).alias("p"), normal_cdf(F.col("x")).alias("n")).collect():
        assert r.p == pytest.approx(Hyperplane().collision(r.x)) and r.n == pytest.approx(0.5 * (1 + math.erf(r.x / math.sqrt(2))), abs=1e-6)


def test_monotone_and_custom():
    grid = [k / 2 for k in range(1, 80)]
    assert all(f.is_monotone(grid) for f in (BitSampling(64), CauchyProjection(5.0), GaussianProjection(5.0)))
    odd = CustomFamily(hash_batch=lambda b, rng: np.zeros(b.n), prob=lambda d: 0.9 if d < 3 else 0.1 + d / 1000)
    assert not odd.is_monotone(grid) and odd.is_monotone(grid, r=2.5)


def test_published_exponents_and_costs():
    assert params.rho(*MinHash().p1p2(0.5, 0.1)) == pytest.approx(0.30, abs=0.005)
    assert params.rho(*Hyperplane().p1p2(0.7, 0.2)) == pytest.approx(0.51, abs=0.005)
    for data, _, _, _, rho, near, close, single, nested, aware in costs.PUBLISHED:
        n = nested / 1002
        memory = n / 1000
        assert costs.io_nested(n, memory) == pytest.approx(nested)
        assert costs.io_single_level(n, rho, 8 if data == "text" else 2) == pytest.approx(single, rel=0.03)
        t1, t2 = costs.io_t1(n, memory, 1, rho, near * n), costs.io_t2(memory, 1, close * n)
        assert t1 > t2 and aware < nested and aware < single and t1 + t2 < aware  # whose constants aren't published


def test_limits_of_the_bound():
    assert costs.io_t1(1e6, 1e6, 10, 0.4, 5e5) + costs.io_t2(1e6, 10, 9e5) == pytest.approx(1e5 + 1.4e6 / 1e7)
    values = [costs.io_t1(1e6, m, 1, 0.4, 1e6) for m in (1e2, 1e3, 1e4)]
    assert values == sorted(values, reverse=True)
    assert costs.overheads(1e6, 1e3, 10, 0.5)["gain"] == pytest.approx(10)
    level = costs.level_equivalence(1 << 20, 1 << 10, 0.5, 0.25)
    assert level["far"] == pytest.approx(level["far_target"]) and level["near"] == pytest.approx(level["near_target"])


def test_parameters():
    plan = params.plan_memory_aware(2000, 128, MinHash(), 0.5, 0.1)
    assert (plan.k, plan.reps, plan.rounds, plan.far_cap) == (2, 8, 33, 8 * 8 * 128)
    tree = params.plan_memory_oblivious(2000, MinHash(), 0.5, 0.1)
    assert (tree.k0, tree.branching, tree.depth, tree.sample) == (2, 4.0, 2, 198)
    assert params.predicted_recall(1.0, 4, 3) == 1 and 0.5 < params.predicted_recall(0.25, 4, 2) < 0.7
    assert params.aware_recall(0.25, 8) > 1 - math.exp(-2) and params.repeats_whp(2000) == 37
    assert params.check_preconditions(60_000, 60, 1, 0.5, 0.25) and not params.check_preconditions(1e6, 1000, 1, 0.4, 0.2)
    with pytest.raises(ValueError):
        params.plan_memory_aware(100, 10, MinHash(), 0.5, 0.5)


def test_branching_moments_match_a_simulation():
    rng = np.random.default_rng(0)
    p, p1, level = 0.5, 1 / 3, 3
    sizes = []
    for _ in range(4000):
        n = 1
        for _ in range(level):
            n = rng.binomial(3 * n, p)
        sizes.append(n)
    want = costs.branching_moments(p, p1, level)
    assert np.mean(sizes) == pytest.approx(want["mean"], rel=0.1) and np.var(sizes) == pytest.approx(want["variance"], rel=0.2)


def test_a_token_of_many_sets_is_hashed_once(monkeypatch):
    rng, hashed = np.random.default_rng(12), []
    batch = Batch.__new__(Batch)
    sets = [np.sort(rng.choice(30, n, replace=False)) for n in (*rng.integers(0, 20, 200), 0, 30)]
    batch.n, batch.kind, batch.starts, batch.tokens = len(sets), "sets", np.r_[0, np.cumsum([len(v) for v in sets])], np.concatenate(sets).astype(np.uint64)
    names = [(0, j) for j in range(40)]
    monkeypatch.setattr(families, "mixed", lambda x, y, f=families.mixed: hashed.append(len(x)) or f(x, y))
    got = MinHash().primitive(batch, 5, names)
    assert sum(hashed) == 30 * len(names)
    for j, name in enumerate(names):
        values = families.mix(np.arange(30, dtype=np.uint64) ^ families.drawn(5, name).integers(0, 1 << 64, dtype=np.uint64))
        assert got[:, j].tolist() == [int(values[v].min()) if len(v) else (1 << 64) - 1 for v in sets]
