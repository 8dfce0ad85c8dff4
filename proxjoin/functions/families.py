"""Locality-sensitive hash families: how a batch of points is hashed, and how likely a pair collides.

A function is named by a tuple of numbers, and its random choices depend on the
seed and that name alone, so every task, retry and engine run draws the same
function without anything being stored. Dense families hash a whole batch under
all functions at once by a matrix product. ``collision`` is given for numbers
and as a column, since emission rules need it for each pair.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Callable, Sequence
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

Name = tuple[int, ...]
#: Tokens that are hashed under all functions before the next ones; functions that make it worth looking for equal tokens.
BLOCK, FEW = 1 << 14, 16


def drawn(seed: int, name: Name) -> np.random.Generator:
    return np.random.default_rng([seed & 0x7FFFFFFF, 0x5EED, *[n & 0x7FFFFFFF for n in name]])


def mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def mixed(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """mix(x) in the place of x, with y as room of the same size."""
    for factor in (0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53, None):
        np.right_shift(x, np.uint64(33), out=y)
        np.bitwise_xor(x, y, out=x)
        if factor:
            np.multiply(x, np.uint64(factor), out=x)
    return x


class Batch:
    """The features of a batch of points: a matrix, a list of words, or numbers of sets with their starts."""

    def __init__(self, column, kind: str):
        self.kind, self.n = kind, len(column)
        if kind == "bits":
            self.words = column.to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
        else:
            starts = column.offsets.to_numpy().astype(np.int64)
            flat = column.values.to_numpy(zero_copy_only=False)[starts[0] : starts[-1]] if self.n else np.zeros(0)
            self.starts = starts - starts[0] if self.n else np.zeros(1, np.int64)
            if kind == "sets":
                self.tokens = flat.astype(np.int64).view(np.uint64)
            else:
                self.matrix = flat.astype(float).reshape(self.n, -1) if self.n else np.zeros((0, 1))

    def joined(self, other: Batch) -> Batch:
        """The points of both, these first."""
        out = object.__new__(Batch)
        out.kind, out.n = self.kind, self.n + other.n
        if self.kind == "bits":
            out.words = np.concatenate([self.words, other.words])
        elif self.kind == "sets":
            out.tokens, out.starts = np.concatenate([self.tokens, other.tokens]), np.r_[self.starts, self.starts[-1] + other.starts[1:]]
        else:
            out.matrix = np.concatenate([m.matrix for m in (self, other) if m.n] or [self.matrix])
        return out

    def take(self, rows: np.ndarray) -> Batch:
        """Some of the points, in the order of their row numbers here."""
        out = object.__new__(Batch)
        out.kind, out.n = self.kind, len(rows)
        if self.kind == "bits":
            out.words = self.words[rows]
        elif self.kind == "sets":
            size = np.diff(self.starts)[rows]
            out.starts = np.r_[0, np.cumsum(size)]
            out.tokens = self.tokens[np.repeat(self.starts[rows] - out.starts[:-1], size) + np.arange(out.starts[-1])]
        else:
            out.matrix = self.matrix[rows]
        return out


@dataclass(frozen=True)
class HashFamily:
    """One primitive family; subclasses say how it hashes and collides."""

    metric = ""
    kind = "dense"

    def primitive(self, batch: Batch, seed: int, names: Sequence[Name]) -> np.ndarray:
        """Values of shape (points, names) as unsigned 64-bit integers."""
        raise NotImplementedError

    def collision(self, measure: float) -> float:
        """The probability that a pair at this distance or similarity has equal values."""
        raise NotImplementedError

    def collision_column(self, measure: Column) -> Column:
        raise NotImplementedError

    def p1p2(self, r: float, cr: float) -> tuple[float, float]:
        return self.collision(r), self.collision(cr)

    def keys(self, batch: Batch, seed: int, names: Sequence[Name], k: int) -> np.ndarray:
        """One 64-bit key for each name, from k functions of the family each."""
        values = self.primitive(batch, seed, [(*n, j) for n in names for j in range(k)]).reshape(batch.n, len(names), k)
        key = np.zeros((batch.n, len(names)), np.uint64)
        for j in range(k):
            key = mix(key ^ (values[:, :, j] + np.uint64(0x9E3779B97F4A7C15 * (j + 1) & (1 << 64) - 1)))
        return key.view(np.int64)

    def is_monotone(self, grid: Sequence[float], r: float | None = None) -> bool:
        """Whether collisions never grow as pairs move apart on an ascending grid; with r, the
        relaxed form: every pair within r collides at least as often as any pair beyond it."""
        similar = self.metric in ("jaccard", "cosine")
        p = [self.collision(x) for x in grid]
        if r is None:
            steps = zip(p[1:], p, strict=False) if similar else zip(p, p[1:], strict=False)
            return all(a >= b - 1e-12 for a, b in steps)
        near = [q for x, q in zip(grid, p, strict=True) if (x >= r if similar else x <= r)]
        rest = [q for x, q in zip(grid, p, strict=True) if not (x >= r if similar else x <= r)]
        return not near or not rest or min(near) >= max(rest) - 1e-12


@dataclass(frozen=True)
class BitSampling(HashFamily):
    """A random coordinate of a 64-bit word: p(d) = 1 - d / dim."""

    dim: int = 64
    metric = "hamming"
    kind = "bits"

    def primitive(self, batch, seed, names):
        at = np.array([drawn(seed, n).integers(self.dim) for n in names], np.uint64)
        return batch.words[:, None] >> at[None, :] & np.uint64(1)

    def keys(self, batch, seed, names, k):
        """All sampled coordinates at once, by the mask of each name."""
        at = np.array([[drawn(seed, (*n, j)).integers(self.dim) for j in range(k)] for n in names], np.uint64).reshape(len(names), k)
        masks = np.bitwise_or.reduce(np.uint64(1) << at, axis=1)
        return mix((batch.words[:, None] & masks[None, :]) ^ np.uint64(0x9E3779B97F4A7C15)).view(np.int64)

    def collision(self, d):
        return max(0.0, 1 - d / self.dim)

    def collision_column(self, d):
        return F.greatest(F.lit(0.0), 1 - d / self.dim)


@dataclass(frozen=True)
class MinHash(HashFamily):
    """The smallest of seeded token hashes: p(s) = s. Empty sets have a value of their own."""

    metric = "jaccard"
    kind = "sets"

    def primitive(self, batch, seed, names):
        out = np.full((batch.n, len(names)), np.iinfo(np.uint64).max, np.uint64)
        some = np.flatnonzero(np.diff(batch.starts) > 0)
        first = batch.starts[:-1][some]
        salts = [drawn(seed, name).integers(0, 1 << 64, dtype=np.uint64) for name in names]
        # a block of tokens stays in the cache for all functions
        edges = [0, *(np.flatnonzero(np.diff(first // BLOCK)) + 1).tolist(), len(some)]
        blocks = [(low, high, slice(first[low], batch.starts[some[high - 1] + 1])) for low, high in zip(edges[:-1], edges[1:], strict=True) if low < high]
        kinds, place = np.unique(batch.tokens, return_inverse=True) if len(names) >= FEW else (batch.tokens, None)
        if 3 * len(kinds) <= len(batch.tokens):  # a token is hashed once for all sets that have it
            y, room = np.empty_like(kinds), np.empty_like(batch.tokens)
            least = np.empty((len(names), len(some)), np.uint64)
            for j, salt in enumerate(salts):
                x = mixed(kinds ^ salt, y)
                for low, high, here in blocks:
                    hashes = np.take(x, place[here], out=room[: here.stop - here.start], mode="clip")
                    np.minimum.reduceat(hashes, first[low:high] - first[low], out=least[j, low:high])
            out[some] = least.T
            return out
        for low, high, here in blocks:
            tokens = batch.tokens[here]
            x, y, least = np.empty_like(tokens), np.empty_like(tokens), np.empty((len(names), high - low), np.uint64)
            for j, salt in enumerate(salts):
                np.bitwise_xor(tokens, salt, out=x)
                np.minimum.reduceat(mixed(x, y), first[low:high] - first[low], out=least[j])
            out[some[low:high]] = least.T
        return out

    def collision(self, s):
        return s

    def collision_column(self, s):
        return s


@dataclass(frozen=True)
class Hyperplane(HashFamily):
    """The side of a random hyperplane: p(s) = 1 - angle / pi."""

    metric = "cosine"

    def primitive(self, batch, seed, names):
        planes = np.stack([drawn(seed, n).standard_normal(batch.matrix.shape[1]) for n in names], axis=1)
        return (batch.matrix @ planes >= 0).astype(np.uint64)

    def keys(self, batch, seed, names, k):
        """The sides themselves as the bits of a key, 63 together at most."""
        key = np.zeros((batch.n, len(names)), np.uint16 if k <= 16 else np.uint64)
        for j in range(k):
            key <<= 1
            key |= batch.matrix @ np.stack([drawn(seed, (*n, j)).standard_normal(batch.matrix.shape[1]) for n in names], axis=1) >= 0
            if j % 63 == 62 or j == k - 1:
                key = mix(key.astype(np.uint64) ^ np.uint64(0x9E3779B97F4A7C15))
        return key.view(np.int64)

    def collision(self, s):
        return 1 - math.acos(max(-1.0, min(1.0, s))) / math.pi

    def collision_column(self, s):
        return 1 - F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), s))) / math.pi


@dataclass(frozen=True)
class Projection(HashFamily):
    """A random projection, shifted and cut into steps of a width."""

    width: float = 1.0

    def _directions(self, rng: np.random.Generator, dim: int) -> np.ndarray:
        raise NotImplementedError

    def primitive(self, batch, seed, names):
        dim, lines, shifts = batch.matrix.shape[1], [], []
        for name in names:
            rng = drawn(seed, name)
            lines.append(self._directions(rng, dim))
            shifts.append(rng.uniform(0, self.width))
        cells = np.floor((batch.matrix @ np.stack(lines, axis=1) + np.array(shifts)) / self.width)
        return np.clip(cells, -(2**62), 2**62).astype(np.int64).view(np.uint64)


@dataclass(frozen=True)
class CauchyProjection(Projection):
    """For l1: p(d) = 2 atan(t) / pi - ln(1 + t^2) / (pi t), t = width / d."""

    metric = "l1"

    def _directions(self, rng, dim):
        return rng.standard_cauchy(dim)

    def collision(self, d):
        if d <= 0:
            return 1.0
        t = self.width / d
        return 2 * math.atan(t) / math.pi - math.log1p(t * t) / (math.pi * t)

    def collision_column(self, d):
        t = self.width / d
        return F.when(d <= 0, F.lit(1.0)).otherwise(2 * F.atan(t) / math.pi - F.log1p(t * t) / (math.pi * t))


def normal_cdf(x: Column) -> Column:
    """The normal distribution function for x >= 0 by a public rational approximation, to 1e-7."""
    t = 1 / (1 + 0.2316419 * x)
    poly = t * (0.319381530 + t * (-0.356563782 + t * (1.781477937 + t * (-1.821255978 + t * 1.330274429))))
    return 1 - F.exp(-x * x / 2) / math.sqrt(2 * math.pi) * poly


@dataclass(frozen=True)
class GaussianProjection(Projection):
    """For l2: p(d) = 1 - 2 Phi(-t) - 2 / (sqrt(2 pi) t) (1 - exp(-t^2 / 2)), t = width / d."""

    metric = "l2"

    def _directions(self, rng, dim):
        return rng.standard_normal(dim)

    def collision(self, d):
        if d <= 0:
            return 1.0
        t = self.width / d
        return math.erf(t / math.sqrt(2)) - 2 / (math.sqrt(2 * math.pi) * t) * (1 - math.exp(-t * t / 2))

    def collision_column(self, d):
        t = self.width / d
        return F.when(d <= 0, F.lit(1.0)).otherwise(2 * normal_cdf(t) - 1 - 2 / (math.sqrt(2 * math.pi) * t) * (1 - F.exp(-t * t / 2)))


@dataclass(frozen=True)
class CustomFamily(HashFamily):
    """A black box: hash_batch(batch, generator) gives one integer for each point, prob the collision probability."""

    hash_batch: Callable[[Batch, np.random.Generator], np.ndarray] = None
    prob: Callable[[float], float] = None
    prob_column: Callable[[Column], Column] | None = None
    metric: str = "l2"
    kind: str = "dense"

    def primitive(self, batch, seed, names):
        return np.stack([np.asarray(self.hash_batch(batch, drawn(seed, n))).astype(np.int64).view(np.uint64) for n in names], axis=1)

    def collision(self, x):
        return self.prob(x)

    def collision_column(self, x):
        if self.prob_column is None:
            raise ValueError("random emission needs the collision probability as a column")
        return self.prob_column(x)


def family_for(metric: str, width: float | None = None, dim: int = 64) -> HashFamily:
    return {"hamming": lambda: BitSampling(dim), "jaccard": MinHash, "cosine": Hyperplane, "l1": lambda: CauchyProjection(width or 1.0), "l2": lambda: GaussianProjection(width or 1.0)}[metric]()


# Portable forms: any engine with MD5 can repeat these.


def md5_unit(tag: str) -> float:
    """52 bits of the MD5 of a tag, inside (0, 1)."""
    return (int(hashlib.md5(tag.encode()).hexdigest()[:13], 16) + 0.5) / 16**13


def md5_coordinate(seed: int, rep: int, j: int, dim: int = 64) -> int:
    return int(md5_unit(f"{seed}:{rep}:{j}") * dim)


def md5_minhash(feat: Column, seed: int, rep: int, j: int) -> Column:
    return F.array_min(F.transform(feat, lambda t: F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:{rep}:{j}:"), t.cast("string"))), 1, 15), 16, 10).cast("long")))


def md5_bits(feat: Column, seed: int, rep: int, k: int) -> Column:
    bits = [F.call_function("shiftrightunsigned", feat, F.lit(md5_coordinate(seed, rep, j))).bitwiseAND(F.lit(1)).cast("string") for j in range(k)]
    return F.concat(*bits)
