"""Exact Jaccard joins of sets in cells of like sizes, without a row for each shared token.

Equal sets are one class and only its smallest id is compared. Classes of sizes half an
octave wide are cut into chunks; two chunks whose sizes allow r make a cell, one group of
the join. A set goes there as a signature: bit j is the parity of how many of its tokens
hash to j. Signatures of two sets differ in at most as many bits as their symmetric
difference has tokens, so a pair beyond what r allows leaves without its tokens; the wider
of two signatures is folded to the narrower. With a filter only pairs that share a token of
their prefixes are looked at, marked in a table of bits in the cell.

What is left is checked by the whole sets, each of which travels once for all its pairs of
a cell. No link is drawn: every pair at least r similar is found. Work on signatures still
grows with the square of the sets, at a bit or so for each token and pair.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import Thresholds
from ..sources.scratch import written
from .hashing import near, result

#: Sizes at which classes begin, sets and bytes of a chunk at most, bits of signatures made at once.
BOUNDS = np.unique([math.ceil(2 ** (k / 2)) for k in range(63)])
SETS, BYTES, STEP = 1 << 15, 32 << 20, 1 << 22
#: Slots of the table of how common tokens are, whose size does not depend on the data.
SLOTS = 20
MIXER = np.uint64(0x9E3779B97F4A7C15)
FILTERS = ("none", "prefix", "positional")


def widths() -> np.ndarray:
    """Bits of a signature by class: a power of two, four or more for each token."""
    return np.array([64] + [max(64, 1 << math.ceil(math.log2(4 * int(b)))) for b in BOUNDS[1:]] + [64])


def commonness(points: DataFrame) -> np.ndarray:
    """How many sets have a token in each slot, by its last bits."""
    slot = F.col("token").bitwiseAND(F.lit((1 << SLOTS) - 1).cast("long"))
    counted = points.select(F.explode("feat").alias("token")).groupBy(slot.alias("slot")).agg(F.count(F.lit(1)).alias("n")).toArrow()
    out = np.zeros(1 << SLOTS, np.int64)
    out[counted.column("slot").to_numpy()] = counted.column("n").to_numpy()
    return out


def classes_of(points: DataFrame, empty: bool = False) -> DataFrame:
    """id, rep: the smallest id with the same set; empty sets have one on request only."""
    named = points.where(F.size("feat") >= (0 if empty else 1)).select("id", F.xxhash64("feat", F.lit(1)).alias("one"), F.xxhash64("feat", F.lit(2)).alias("two"), F.size("feat").alias("size"))
    named = written(named, "names")
    reps = named.groupBy("one", "two", "size").agg(F.min("id").alias("rep"))
    return written(named.join(reps, ["one", "two", "size"]).select("id", "rep"), "classes")


def marks(sets: DataFrame, r: float, counts: Broadcast | None) -> DataFrame:
    """id, class, size, sig, prefix (32 bits of each of the rarest tokens, the rarest first; empty without counts)."""
    width_of = widths()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            sizes = whole.column(1).value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            cuts = np.cumsum(width_of[np.searchsorted(BOUNDS, sizes, "right")]) // STEP
            edges = [0, *(np.flatnonzero(np.diff(cuts)) + 1).tolist(), len(sizes)]
            for first, last in zip(edges[:-1], edges[1:], strict=True):
                batch, size = whole.slice(first, last - first), sizes[first:last]
                if not len(size):
                    continue
                tokens = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
                which = np.repeat(np.arange(len(size)), size)
                level = np.searchsorted(BOUNDS, size, "right")
                width = width_of[level]
                start = np.cumsum(width) - width
                low = tokens * MIXER >> np.uint64(32)
                place = start[which] + (low & (width - 1).astype(np.uint64)[which]).astype(np.int64)
                bits = np.packbits((np.bincount(place, minlength=int(width.sum())) & 1).astype(np.uint8), bitorder="little").tobytes()
                sig = [bits[s // 8 : (s + w) // 8] for s, w in zip(start.tolist(), width.tolist(), strict=True)]
                prefix = [b""] * len(size)
                if counts is not None:
                    order = np.lexsort((tokens, counts.value[(tokens & np.uint64((1 << SLOTS) - 1)).astype(np.int64)], which))
                    begin = np.cumsum(size) - size
                    ranked, most = low[order].astype("<u4"), (size - np.ceil(r * size - 1e-9) + 1).astype(np.int64)
                    prefix = [ranked[b : b + m].tobytes() for b, m in zip(begin.tolist(), most.tolist(), strict=True)]
                yield pa.record_batch([batch.column(0), pa.array(level, pa.int32()), pa.array(size), pa.array(sig, pa.binary()), pa.array(prefix, pa.binary())], names=["id", "class", "size", "sig", "prefix"])

    return sets.select("id", "feat").mapInArrow(run, "id long, class int, size long, sig binary, prefix binary")


def compatible(r: float) -> np.ndarray:
    """Whether sets of the one class may be at least r similar to sets of the other, no smaller one."""
    first = np.r_[0, BOUNDS]
    last = np.r_[BOUNDS - 1, np.iinfo(np.int64).max >> 1]
    return np.triu(first[None, :] * r <= last[:, None] + 1e-6)


def spread(marked: DataFrame, r: float, prefixed: bool) -> tuple[DataFrame, int]:
    """marked with cell and side, a row for each cell; and how many cells there are."""
    counted = {row["class"]: row.n for row in marked.groupBy("class").agg(F.count(F.lit(1)).alias("n")).collect()}
    width, fits = widths(), compatible(r)
    each = lambda c: int(width[c]) * (3 if prefixed else 1) // 8 + 64
    parts = {c: max(1, -(-n // SETS), -(-n * each(c) // BYTES)) for c, n in counted.items()}
    code = lambda a, i, b, j: ((a * 65536 + i) * 64 + b) * 65536 + j

    def cells_of(c: int, i: int) -> list[tuple[int, int]]:
        up = [(code(c, i, d, j), 0) for d in parts if d >= c and fits[c, d] for j in range(i if d == c else 0, parts[d])]
        return up + [(code(d, j, c, i), 1) for d in parts if d <= c and fits[d, c] for j in range(i if d == c else parts[d])]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            level, part = batch.column(1).to_numpy(), batch.column(2).to_numpy()
            for c, i in sorted(set(zip(level.tolist(), part.tolist(), strict=True))):
                some = batch.filter(pa.array((level == c) & (part == i)))
                for cell, side in cells_of(c, i):
                    n = some.num_rows
                    yield pa.record_batch([pa.array(np.full(n, cell)), pa.array(np.full(n, side, np.int32)), some.column(0), *some.columns[3:]], names=["cell", "side", "id", "size", "sig", "prefix"])

    count = F.element_at(F.create_map(*[F.lit(v) for kv in parts.items() for v in kv]), F.col("class")) if parts else F.lit(1)
    placed = marked.select("id", "class", F.pmod(F.xxhash64("id", F.lit(23)), count).cast("int").alias("part"), "size", "sig", "prefix")
    cells = sum(len([1 for cell, side in cells_of(c, i) if side == 0]) for c in parts for i in range(parts[c]))
    return placed.mapInArrow(run, "cell long, side int, id long, size long, sig binary, prefix binary"), cells


class Side:
    """The sets of one side of a cell, the smallest first."""

    def __init__(self, table: pa.Table, prefixed: bool):
        order = np.argsort(table.column("size").to_numpy(), kind="stable")
        table = table.take(pa.array(order)).combine_chunks()
        self.ids, self.size = table.column("id").to_numpy(), table.column("size").to_numpy()
        self.sig = np.frombuffer(b"".join(table.column("sig").to_pylist()), "<u8").reshape(len(order), -1)
        if prefixed:
            told = table.column("prefix").to_pylist()
            length = np.array([len(p) // 4 for p in told])
            self.stop = np.cumsum(length)
            self.token, self.which = np.frombuffer(b"".join(told), "<u4"), np.repeat(np.arange(len(order)), length)
            self.place = np.arange(len(self.token)) - (self.stop - length)[self.which]

    def folded(self, words: int) -> np.ndarray:
        return np.bitwise_xor.reduce(self.sig.reshape(len(self.ids), -1, words), axis=1)


def enough(size_a: np.ndarray, size_b: np.ndarray, r: float) -> np.ndarray:
    """Bits that signatures may differ in at most, none for sizes that rule r out."""
    most = np.floor((size_a + size_b) * ((1 - r) / (1 + r)) + 1e-6).astype(np.int64)
    return np.where((size_a * r <= size_b + 1e-9) & (size_b * r <= size_a + 1e-9), most, -1)


def all_like(a: Side, b: Side, own: bool, r: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places of all pairs that their signatures allow."""
    one, two = a.sig.T.copy(), b.folded(a.sig.shape[1]).T.copy()
    for i in range(0, len(a.ids), 64):
        size = a.size[i : i + 64]
        first, last = np.searchsorted(b.size, size[0] * r - 1e-6), np.searchsorted(b.size, size[-1] / r + 1e-6, "right")
        for j in range(max(first, i) if own else first, last, 4096):
            stop = min(j + 4096, last)
            differ = np.zeros((len(size), stop - j), np.uint32 if len(one) > 1000 else np.uint16)
            for word_a, word_b in zip(one[:, i : i + 64], two[:, j:stop], strict=True):
                differ += np.bitwise_count(word_a[:, None] ^ word_b[None, :])
            x, y = np.nonzero(differ <= enough(size[:, None], b.size[None, j:stop], r))
            yield x + i, y + j


def sharing(a: Side, b: Side, own: bool, r: float, positional: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places of the pairs that share a token of their prefixes, with enough tokens left after it if positional, and that their signatures allow."""
    one, two = a.sig, b.folded(a.sig.shape[1])
    order = np.argsort(b.token, kind="stable")
    token, which, place = b.token[order], b.which[order], b.place[order]
    for i in range(0, len(a.ids), 1024):
        end = min(i + 1024, len(a.ids))
        here = slice(a.stop[i - 1] if i else 0, a.stop[end - 1])
        low, high = np.searchsorted(token, a.token[here]), np.searchsorted(token, a.token[here], "right")
        met = np.zeros((end - i, len(b.ids)), bool)
        steps = np.cumsum(high - low) // STEP
        edges = [0, *(np.flatnonzero(np.diff(steps)) + 1).tolist(), len(low)]
        for s, t in zip(edges[:-1], edges[1:], strict=True):
            n = (high - low)[s:t]
            mine = np.repeat(np.arange(s, t) + here.start, n)
            theirs = np.arange(n.sum()) + np.repeat(low[s:t] - (np.cumsum(n) - n), n)
            x, y = a.which[mine], which[theirs]
            if positional:
                rest = np.minimum(a.size[x] - a.place[mine], b.size[y] - place[theirs])  # with the shared one
                keep = rest >= np.ceil(r / (1 + r) * (a.size[x] + b.size[y]) - 1e-9)
                x, y = x[keep], y[keep]
            met[x - i, y] = True
        x, y = np.nonzero(met)
        for s in range(0, len(x), STEP // max(8, one.shape[1])):
            u, v = x[s : s + STEP // max(8, one.shape[1])] + i, y[s : s + STEP // max(8, one.shape[1])]
            sized = np.flatnonzero(enough(a.size[u], b.size[v], r) >= 0)
            u, v = u[sized], v[sized]
            like = np.bitwise_count(one[u] ^ two[v]).sum(axis=1) <= enough(a.size[u], b.size[v], r)
            yield u[like], v[like]


def allowed(cells: DataFrame, number: int, r: float, kind: str) -> DataFrame:
    """cell, a, b: pairs of sets that the filter and the signatures leave."""

    def compare(table: pa.Table) -> pa.Table:
        side = table.column("side").to_numpy()
        own = not side.any()
        a = Side(table.filter(pa.array(side == 0)), kind != "none")
        b = a if own else Side(table.filter(pa.array(side == 1)), kind != "none")
        found = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
        if len(a.ids):
            for x, y in all_like(a, b, own, r) if kind == "none" else sharing(a, b, own, r, kind == "positional"):
                keep = x < y if own else slice(None)
                found.append((a.ids[x[keep]], b.ids[y[keep]]))
        left, right = (np.concatenate(v) for v in zip(*found, strict=True))
        return pa.table({"cell": pa.array(np.full(len(left), table.column("cell")[0].as_py())), "a": pa.array(left), "b": pa.array(right)})

    return cells.repartition(max(16, number), "cell").groupBy("cell").applyInArrow(compare, "cell long, a long, b long")


def verified(pairs: DataFrame, sets: DataFrame, number: int) -> DataFrame:
    """a, b, value: the similarity of each pair from the whole sets."""

    def compare(pairs: pa.Table, sets: pa.Table) -> pa.Table:
        found = dict(zip(sets.column("id").to_pylist(), (np.frombuffer(v.as_buffer(), "<i8") for v in sets.column("data")), strict=True))
        value = np.empty(pairs.num_rows)
        for k, (a, b) in enumerate(zip(pairs.column("a").to_pylist(), pairs.column("b").to_pylist(), strict=True)):
            x, y = found[a], found[b]
            common = len(np.intersect1d(x, y, assume_unique=True))
            value[k] = common / (len(x) + len(y) - common)
        return pa.table({"a": pairs.column("a"), "b": pairs.column("b"), "value": pa.array(value)})

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw = [v.values.to_numpy(zero_copy_only=False).astype("<i8").tobytes() for v in batch.column(1)]
            yield pa.record_batch([batch.column(0), pa.array(raw, pa.binary())], names=["id", "data"])

    wanted = pairs.select(F.col("cell").alias("of"), F.col("a").alias("id")).union(pairs.select("cell", "b")).distinct()
    data = sets.select("id", "feat").mapInArrow(packed, "id long, data binary").join(wanted, "id")
    ends = [f.repartition(max(16, number), by).groupBy(by) for f, by in ((pairs, "cell"), (data, "of"))]
    return ends[0].cogroup(ends[1]).applyInArrow(compare, "a long, b long, value double")


def near_values(points: DataFrame, at: Thresholds, kind: str = "none", empty: bool = False) -> DataFrame:
    """id_l, id_r, value: all pairs of sets at least r similar, which must be above 0, with copies; empty sets, which are alike, on request only."""
    if kind not in FILTERS or at.metric != "jaccard" or not 0 < at.r <= 1:
        raise ValueError(f"wants a Jaccard threshold above 0 and a filter of {FILTERS}")
    spark = points.sparkSession
    classes = classes_of(points, empty)
    sets = points.where(F.size("feat") > 0).join(classes.where("id = rep").select("id"), "id").select("id", "feat")
    counts = None if kind == "none" else spark.sparkContext.broadcast(commonness(sets))
    marked = written(marks(sets, at.r, counts), "marks")
    cells, number = spread(marked, at.r, kind != "none")
    pairs = written(allowed(cells, number, at.r, kind), "allowed")
    if counts is not None:
        counts.destroy()
    values = written(verified(pairs, sets, number).where(at.near(F.col("value"))), "values")
    between = values.join(classes.toDF("x", "a"), "a").join(classes.toDF("y", "b"), "b").select("x", "y", "value")
    within = classes.toDF("x", "rep").join(classes.toDF("y", "rep"), "rep").where("x < y").select("x", "y", F.lit(1.0).alias("value"))
    return between.union(within).select(F.least("x", "y").alias("id_l"), F.greatest("x", "y").alias("id_r"), "value")


def exact_set_join(points: DataFrame, at: Thresholds, kind: str = "none") -> DataFrame:
    """id_l, id_r, dist of all near pairs, by signatures alone or behind a prefix or positional filter."""
    return result(near(near_values(points, at, kind), at))
