"""Joins of points with short features in cells: squares of chunks of the points, each one group of Spark's.

A chunk holds so many points at most, whatever the input, and a feature travels once for each chunk, so
no row is made for a pair before it is known to be near. Pairs of rows with the same id are none.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.families import Batch, HashFamily, Name
from ..functions.metrics import Thresholds
from ..sources.scratch import written
from .hashing import dense, near, result

CHUNK, CHUNK_BITS = 8192, 16384
#: Chunks at least, so that few points have cells for all cores too, unless chunks would be smaller than so many points.
PARTS, LEAST = 6, 1024
#: Repetitions that are hashed at once.
TAGS = 64
#: Meetings that are looked at together.
MEETINGS = 1 << 20
#: Slack of a distance or similarity by a matrix product, relative to the lengths; what it leaves is measured again.
SLACK = 1e-9

PAIRS = "id_l long, id_r long, value double"
Compare = Callable[..., pa.Table]


def in_cells(points: DataFrame, kind: str, compare: Compare, schema: str, chunk: int = CHUNK, carry: str | None = None) -> DataFrame:
    """What compare makes of each cell: ids and features of both its sides, and the numbers in the column carry; with own, they are the same chunk."""
    points = points.where(F.col("id").isNotNull() & F.col("feat").isNotNull())
    count = points.count()
    parts = max(1, -(-count // chunk), min(PARTS, -(-count // LEAST)))
    more = [carry] if carry else []
    placed = points.select("id", "feat", *more, F.pmod(F.xxhash64("id", F.lit(29)), F.lit(parts)).cast("int").alias("part")).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    cells = placed.select((F.least("part", "other") * F.lit(parts).cast("long") + F.greatest("part", "other")).alias("cell"), (F.col("part") > F.col("other")).alias("second"), "id", "feat", *more)

    def run(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        second = table.column("second")
        own = table.column("cell")[0].as_py() % (parts + 1) == 0
        sides = [table.filter(pa.array(~second.to_numpy())), table.filter(second)]
        a, b = ((t.column("id").to_numpy(), Batch(column(t), kind)) for t in (sides[0], sides[0 if own else 1]))
        return compare(*a, *b, own, *[t.column(c).to_numpy() for c in more for t in (sides[0], sides[0 if own else 1])])

    return cells.repartition(max(16, parts * (parts + 1) // 2), "cell").groupBy("cell").applyInArrow(run, schema)


def column(table: pa.Table) -> pa.Array:
    whole = table.column("feat").combine_chunks()
    return whole.chunk(0) if isinstance(whole, pa.ChunkedArray) and whole.num_chunks else whole


def ordered(ids_a: np.ndarray, ids_b: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The smaller and the larger id of each pair, and which pairs have two."""
    a, b = ids_a[x], ids_b[y]
    return np.minimum(a, b), np.maximum(a, b), a != b


def products(a: Batch, b: Batch, own: bool, step: int = 512) -> Iterator[tuple[int, int, np.ndarray]]:
    """First row, first column and dot products, of stripes of all pairs; with own a stripe begins at its own rows."""
    for i in range(0, a.n, step):
        j = i if own else 0
        yield i, j, a.matrix[i : i + step] @ b.matrix[j:].T


def closest_pairs(points: DataFrame, at: Thresholds, k: int) -> DataFrame:
    """id_l, id_r, dist: the k near pairs by l2 that come first by (dist, id_l, id_r)."""

    def compare(ids_a, a, ids_b, b, own):
        best = [np.zeros(0), np.zeros(0, np.int64), np.zeros(0, np.int64)]
        bound = at.r
        size_a, size_b = ((m.matrix**2).sum(axis=1) for m in (a, b))
        for i, j, dots in products(a, b, own):
            square = size_a[i : i + len(dots), None] + size_b[None, j:]
            # dist is rounded to six digits, so pairs up to half a digit beyond may stand as early
            x, y = np.nonzero(square - 2 * dots <= (bound + 1e-6) ** 2 + SLACK * square)
            x, y = x + i, y + j
            if own:
                x, y = x[x < y], y[x < y]
            value = dense("l2", a.matrix[x], b.matrix[y])
            low, high, two = ordered(ids_a, ids_b, x, y)
            keep = two & (value <= at.r)
            best = [np.r_[old, new[keep]] for old, new in zip(best, (value, low, high), strict=True)]
            order = np.lexsort((best[2], best[1], np.round(best[0], 6)))[:k]
            best = [v[order] for v in best]
            if len(order) == k:
                bound = min(bound, best[0][-1])
        return pa.table({"id_l": best[1], "id_r": best[2], "value": best[0]})

    return result(near(in_cells(points, "dense", compare, "id_l long, id_r long, value double"), at)).orderBy("dist", "id_l", "id_r").limit(k)


def met_at(keys_a: np.ndarray, keys_b: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places of all pairs with equal keys, by buckets of the keys' first 16 bits, about MEETINGS at once."""
    keys_a, keys_b = np.ascontiguousarray(keys_a).view(np.uint64), np.ascontiguousarray(keys_b).view(np.uint64)
    short_a, short_b = ((v >> np.uint64(48)).astype(np.uint16) for v in (keys_a, keys_b))
    order = np.argsort(short_b, kind="stable")
    size = np.bincount(short_b, minlength=1 << 16)
    start = np.cumsum(size) - size
    n = size[short_a]
    cuts = np.cumsum(n) // MEETINGS
    edges = [0, *(np.flatnonzero(np.diff(cuts)) + 1).tolist(), len(n)]
    for low, high in zip(edges[:-1], edges[1:], strict=True):
        some = n[low:high]
        x = np.repeat(np.arange(low, high), some)
        y = order[np.arange(len(x)) + np.repeat(start[short_a[low:high]] - (np.cumsum(some) - some), some)]
        same = keys_a[x] == keys_b[y]
        yield x[same], y[same]


def keys_of(a: Batch, b: Batch, own: bool, family: HashFamily, seed: int, names: list[Name], k: int) -> tuple[np.ndarray, np.ndarray]:
    """Keys of both sides, whose functions are drawn once."""
    keys = family.keys(a if own else a.joined(b), seed, names, k).T.copy().T
    return keys[: a.n], keys[0 if own else a.n :]


def ever_met(x: np.ndarray, y: np.ndarray, a: Batch, b: Batch, own: bool, family: HashFamily, seed: int, names: list[Name], k: int) -> np.ndarray:
    """Which of the pairs of rows have an equal key in some repetition. A pair that has met, and a point without other pairs, is not hashed again."""
    met, left = np.zeros(len(x), bool), np.arange(len(x), dtype=np.int32)
    for first in range(0, len(names), TAGS):
        if not len(left):
            break
        u, v = x[left], y[left]
        rows, places = [], []
        for n, here in ((a.n, [u, v] if own else [u]), (b.n, [] if own else [v])):
            some = np.zeros(n, bool)
            for w in here:
                some[w] = True
            rows.append(np.flatnonzero(some))
            places += [(np.cumsum(some, dtype=np.int32) - 1)[w] for w in here]
        keys_a, keys_b = (np.ascontiguousarray(m) for m in keys_of(a.take(rows[0]), b.take(rows[1]), own, family, seed, names[first : first + TAGS], k))
        hit = np.zeros(len(left), bool)
        for s in range(0, len(left), 1 << 14):
            hit[s : s + (1 << 14)] = (keys_a[places[0][s : s + (1 << 14)]] == keys_b[places[1][s : s + (1 << 14)]]).any(axis=1)
        met[left[hit]] = True
        left = left[~hit]
    return met


def gathered(found: Iterator[tuple[np.ndarray, np.ndarray]], most: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The pairs of rows in pieces of about so many."""
    xs, ys, held = [], [], 0
    for x, y in found:
        xs.append(x.astype(np.int32))
        ys.append(y.astype(np.int32))
        held += len(x)
        if held >= most:
            yield np.concatenate(xs), np.concatenate(ys)
            xs, ys, held = [], [], 0
    if held:
        yield np.concatenate(xs), np.concatenate(ys)


def near_met_bits(points: DataFrame, at: Thresholds, family: HashFamily, seed: int, names: list[Name], k: int) -> DataFrame:
    """id_l, id_r, value: near pairs of words with an equal key in some repetition. A word is measured wherever it meets, since that is cheap."""

    def compare(ids_a, a, ids_b, b, own):
        found = np.zeros(0, np.int64)
        for first in range(0, len(names), TAGS):
            keys_a, keys_b = keys_of(a, b, own, family, seed, names[first : first + TAGS], k)
            more, held = [found], 0
            for tag in range(keys_a.shape[1]):
                for x, y in met_at(keys_a[:, tag], keys_b[:, tag]):
                    close = np.bitwise_count(a.words[x] ^ b.words[y]) <= at.r
                    more.append(x[close] * b.n + y[close])
                    held += len(more[-1])
                    if held > MEETINGS:
                        found = np.unique(np.concatenate(more))
                        more, held = [found], 0
            found = np.unique(np.concatenate(more))
        x, y = found // max(1, b.n), found % max(1, b.n)
        return told(ids_a, ids_b, x, y, np.bitwise_count(a.words[x] ^ b.words[y]).astype(float), own)

    return in_cells(points, "bits", compare, PAIRS, CHUNK_BITS)


def near_met_dense(points: DataFrame, at: Thresholds, family: HashFamily, seed: int, names: list[Name], k: int) -> DataFrame:
    """id_l, id_r, value: near pairs of vectors with an equal key in some repetition. Pairs are measured first, so only near ones are looked up in the buckets."""

    def compare(ids_a, a, ids_b, b, own):
        size_a, size_b = (np.sqrt((m.matrix**2).sum(axis=1)) for m in (a, b))

        def close() -> Iterator[tuple[np.ndarray, np.ndarray]]:
            for i, j, dots in products(a, b, own):
                scale = size_a[i : i + len(dots), None] * size_b[None, j:]
                x, y = np.nonzero((scale > 0) & (dots >= (at.r - SLACK) * scale))
                x, y = x + i, y + j
                keep = x < y if own else slice(None)
                yield x[keep], y[keep]

        xs, ys = [np.zeros(0, np.int32)], [np.zeros(0, np.int32)]
        for x, y in gathered(close(), 4 * MEETINGS):
            met = ever_met(x, y, a, b, own, family, seed, names, k)
            xs.append(x[met])
            ys.append(y[met])
        x, y = np.concatenate(xs), np.concatenate(ys)
        return told(ids_a, ids_b, x, y, dense(at.metric, a.matrix[x], b.matrix[y]), own)

    return in_cells(points, "dense", compare, PAIRS)


def told(ids_a, ids_b, x, y, value, own) -> pa.Table:
    low, high, two = ordered(ids_a, ids_b, x, y)
    if own:
        two &= x < y
    return pa.table({"id_l": low[two], "id_r": high[two], "value": pa.array(value[two], from_pandas=True)})


def near_met(points: DataFrame, at: Thresholds, family: HashFamily, seed: int, names: list[Name], k: int) -> DataFrame:
    """id_l, id_r, value: the near pairs that met in a bucket; copies, which meet in every one, are compared as one point."""
    join = {"hamming": near_met_bits, "cosine": near_met_dense}[at.metric]
    classes = points.select("id", "feat").where("id is not null and feat is not null")
    reps = written(classes.groupBy("feat").agg(F.min("id").alias("id")), "reps")
    values = written(join(reps.select("id", "feat"), at, family, seed, names, k).where(at.near(F.col("value"))), "values")
    of = written(classes.join(reps.select("feat", F.col("id").alias("rep")), "feat").select("id", "rep"), "members")
    between = values.join(of.toDF("x", "id_l"), "id_l").join(of.toDF("y", "id_r"), "id_r").select("x", "y", "value")
    alike = reps.withColumn("value", at.measure(F.col("feat"), F.col("feat"))).where(at.near(F.col("value"))).select(F.col("id").alias("rep"), "value")
    within = of.toDF("x", "rep").join(of.toDF("y", "rep"), "rep").where("x < y").join(alike, "rep").select("x", "y", "value")
    return between.union(within).select(F.least("x", "y").alias("id_l"), F.greatest("x", "y").alias("id_r"), "value")


def l1_halved(points: DataFrame, at: Thresholds, leaf: int) -> DataFrame:
    """id_l, id_r, value: near pairs by l1, where cells are halved on both sides until a leaf. Sides stand in the order
    of their totals, so a quadrant whose totals are further apart than r, and with them its distances, ends at once."""

    def compare(ids_a, a, ids_b, b, own):
        sides = []
        for batch in (a, b):
            m = batch.matrix if batch.n else np.zeros((0, max(a.matrix.shape[1], b.matrix.shape[1])))
            order = np.argsort(m.sum(axis=1), kind="stable")
            m = np.ascontiguousarray(m[order].T)
            small = bool((m == np.round(m)).all() and np.abs(m).sum(axis=0).max(initial=0) < 1 << 14)
            sides.append((order, m, m.sum(axis=0), small))
        (order_a, left, total_a, small_a), (order_b, right, total_b, small_b) = sides
        if small_a and small_b:
            left, right = left.astype(np.int16), right.astype(np.int16)
        slack = at.r * (1 + SLACK) + SLACK
        found = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        todo = [(0, a.n, 0, b.n)]
        while todo:
            i, i_end, j, j_end = todo.pop()
            if i == i_end or j == j_end or own and j_end <= i or total_a[i] - total_b[j_end - 1] > slack or total_b[j] - total_a[i_end - 1] > slack:
                continue
            if max(i_end - i, j_end - j) > leaf:
                half, other = (i + i_end) // 2, (j + j_end) // 2
                todo += [(p, q, s, t) for p, q in ((i, half), (half, i_end)) for s, t in ((j, other), (other, j_end))]
                continue
            away = np.zeros((i_end - i, j_end - j), left.dtype if left.dtype == right.dtype else float)
            for u, v in zip(left[:, i:i_end], right[:, j:j_end], strict=True):
                away += np.abs(u[:, None] - v[None, :])
            x, y = np.nonzero(away <= at.r)
            found.append((x + i, y + j, away[x, y].astype(float)))
        x, y, value = (np.concatenate(v) for v in zip(*found, strict=True))
        # with own both sides have the same order, so each pair is found with its places either way round, and once with the first smaller
        keep = x < y if own else slice(None)
        return told(ids_a, ids_b, order_a[x[keep]], order_b[y[keep]], value[keep], False)

    return in_cells(points, "dense", compare, PAIRS)


def collision_counts(points: DataFrame, at: Thresholds, family: HashFamily, seed: int, names: list[Name], k: int) -> DataFrame:
    """One row: meetings of words in all repetitions by class (near, grey, far), and how many near and grey pairs there are."""

    def compare(ids_a, a, ids_b, b, own):
        codes, whole = [], 0
        for first in range(0, len(names), TAGS):
            keys_a, keys_b = keys_of(a, b, own, family, seed, names[first : first + TAGS], k)
            for u, v in zip(keys_a.T, keys_b.T, strict=True):
                _, code = np.unique(u if own else np.concatenate([u, v]), return_inverse=True)
                u, v = code[: a.n], code[0 if own else a.n :]
                most = int(code.max(initial=-1)) + 1
                pairs = int((np.bincount(u, minlength=most) * np.bincount(v, minlength=most)).sum())
                whole += (pairs - a.n) // 2 if own else pairs
                codes.append(code.astype(np.uint16 if most <= 1 << 16 else np.uint32))
        codes = np.stack(codes, axis=1)
        keys_a, keys_b = codes[: a.n], codes[0 if own else a.n :]
        step = max(1, 16 * MEETINGS // len(names))
        met, size = [0, 0], [0, 0]
        for i in range(0, a.n, 256):
            j = i if own else 0
            away = np.bitwise_count(a.words[i : i + 256, None] ^ b.words[None, j:])
            x, y = np.nonzero(away <= at.cr)
            grey = away[x, y] > at.r
            x, y = x + i, y + j
            if own:
                x, y, grey = x[x < y], y[x < y], grey[x < y]
            for kind in (0, 1):
                u, v = x[grey == kind], y[grey == kind]
                size[kind] += len(u)
                met[kind] += sum(int(np.count_nonzero(keys_a[u[s : s + step]] == keys_b[v[s : s + step]])) for s in range(0, len(u), step))
        return pa.table({"near": [met[0]], "grey": [met[1]], "far": [whole - sum(met)], "near_pairs": [size[0]], "grey_pairs": [size[1]]})

    names_ = ("near", "grey", "far", "near_pairs", "grey_pairs")
    rows = in_cells(points, "bits", compare, ", ".join(f"{c} long" for c in names_), CHUNK_BITS)
    return rows.agg(*[F.coalesce(F.sum(c), F.lit(0)).cast("long").alias(c) for c in names_])


def links_met(points: DataFrame, at: Thresholds, family: HashFamily, seed: int, names: list[Name], k: int) -> DataFrame:
    """id, class_id, links of sets: the smallest id with the same set, and how many other points are near it and met it in a bucket.
    Pairs are measured first, so only near ones are looked up in the buckets."""

    def compare(ids_a, a, ids_b, b, own, copies_a, copies_b):
        kinds, token = np.unique(np.concatenate([a.tokens, b.tokens]), return_inverse=True)
        sides, size = [], [np.diff(a.starts), np.diff(b.starts)]
        for n, mine, which in ((a.n, size[0], token[: len(a.tokens)]), (b.n, size[1], token[len(a.tokens) :])):
            sides.append((np.repeat(np.arange(n), mine), which))

        def close() -> Iterator[tuple[np.ndarray, np.ndarray]]:
            for i in range(0, a.n, 256):
                end, j = min(i + 256, a.n), i if own else 0
                both = np.zeros((end - i, b.n - j), np.float32)
                for t in range(0, len(kinds), 1024):
                    blocks = []
                    for (row, which), low, high in zip(sides, (i, j), (end, b.n), strict=True):
                        some = (row >= low) & (row < high) & (which >= t) & (which < t + 1024)
                        block = np.zeros((high - low, min(1024, len(kinds) - t)), np.float32)
                        block[row[some] - low, which[some] - t] = 1
                        blocks.append(block)
                    both += blocks[0] @ blocks[1].T
                either = size[0][i:end, None].astype(np.float32) + size[1][None, j:] - both
                x, y = np.nonzero(both >= np.float32(at.r - 1e-4) * either)
                common = both[x, y].astype(np.int64)
                x, y = x + i, y + j
                either = size[0][x] + size[1][y] - common
                keep = np.where(either == 0, 1.0, common / np.maximum(either, 1)) >= at.r
                if own:
                    keep &= x < y
                yield x[keep], y[keep]

        links_a, links_b = np.zeros(a.n, np.int64), np.zeros(b.n, np.int64)
        for x, y in gathered(close(), 4 * MEETINGS):
            met = ever_met(x, y, a, b, own, family, seed, names, k)
            x, y = x[met], y[met]
            for links, mine, theirs, copies in ((links_a, x, y, copies_b), (links_a if own else links_b, y, x, copies_a)):
                links += np.bincount(mine, copies[theirs], len(links)).astype(np.int64)
        ids, links = (ids_a, links_a) if own else (np.r_[ids_a, ids_b], np.r_[links_a, links_b])
        return pa.table({"id": ids, "links": links})

    classes = written(points.where("id is not null and feat is not null").groupBy("feat").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("copies")), "classes")
    links = in_cells(classes, "sets", compare, "id long, links long", carry="copies").groupBy("id").agg(F.sum("links").alias("links"))
    named = classes.join(links, "id").select("feat", F.col("id").alias("class_id"), (F.col("links") + F.col("copies") - 1).alias("links"))
    return points.join(named, "feat").select("id", "class_id", "links")


def close_pairs(points: DataFrame, at: Thresholds) -> DataFrame:
    """id_l, id_r, value: all pairs of vectors at least cr similar by cosine; sums run in the order of the dimensions, as those of columns do."""

    def added(m: np.ndarray, n: np.ndarray) -> np.ndarray:
        total = np.zeros(len(m))
        for u, v in zip(m.T, n.T, strict=True):
            total += u * v
        return total

    def compare(ids_a, a, ids_b, b, own):
        size_a, size_b = (np.sqrt(added(m.matrix, m.matrix)) for m in (a, b))
        found = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        for i, j, dots in products(a, b, own, 128):
            scale = size_a[i : i + len(dots), None] * size_b[None, j:]
            x, y = np.nonzero((scale > 0) & (dots >= (at.cr - SLACK) * scale))
            x, y = x + i, y + j
            if own:
                x, y = x[x < y], y[x < y]
            value = added(a.matrix[x], b.matrix[y]) / (size_a[x] * size_b[y])
            close = value >= at.cr
            found.append((x[close], y[close], value[close]))
        x, y, value = (np.concatenate(v) for v in zip(*found, strict=True))
        return told(ids_a, ids_b, x, y, value, False)

    return in_cells(points, "dense", compare, PAIRS, CHUNK // 2)
