"""Meetings of sets under the keys of many repetitions, without a row for each key or for each pair that met.

A group of the join holds the keys of some repetitions for all sets (or a slice of the keys of one, where
those are too many for a task), one row for each set, beside a signature: bit j is the parity of how many
tokens hash to j. Two signatures differ in at most as many bits as the symmetric difference has tokens, so
of the pairs with an equal key those beyond what r allows end there; no near pair does. Equal sets count
once in a group, under their smallest id. What is left is checked by the whole sets in cells of sets that
met each other, so that a set travels once for many pairs. Repetitions are taken in passes, and what one
pass has shuffled may go before the next.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.families import Batch, HashFamily, Name
from ..functions.metrics import Thresholds
from ..sources.scratch import written

#: Bytes of a group and of a pass at most, repetitions of a group at most, pairs that are looked at together.
GROUP, PASS, TAGS, STEP = 160 << 20, 1 << 30, 16, 1 << 20
#: Bits of a signature at least; bits of signatures made at once; bytes of a set's row without keys and signature.
FLOOR, BITS, ROW = 512, 1 << 22, 88
#: Classes for each cell of the check, and pairs of a cell from one leader.
CELL, SHARE = 4096, 1 << 17
MIXER = np.uint64(0x9E3779B97F4A7C15)


def widths(size: np.ndarray) -> np.ndarray:
    """Bits of signatures: a power of two, four or more for each token."""
    return np.maximum(FLOOR, 1 << np.ceil(np.log2(4.0 * np.maximum(size, 1))).astype(np.int64))


def signatures(tokens: np.ndarray, size: np.ndarray) -> pa.Array:
    out, stop = [], np.r_[0, np.cumsum(size)]
    width = widths(size)
    edges = [0, *(np.flatnonzero(np.diff(np.cumsum(width) // BITS)) + 1).tolist(), len(size)]
    for first, last in zip(edges[:-1], edges[1:], strict=True):
        mine = width[first:last]
        start = np.cumsum(mine) - mine
        low = (tokens[stop[first] : stop[last]] * MIXER >> np.uint64(32)).astype(np.int64)
        which = np.repeat(np.arange(last - first), size[first:last])
        place = start[which] + (low & (mine - 1)[which])
        out.append(np.packbits((np.bincount(place, minlength=int(mine.sum())) & 1).astype(np.uint8), bitorder="little"))
    return binaries(np.concatenate(out) if out else np.zeros(0, np.uint8), width // 8)


def binaries(data: np.ndarray, length: np.ndarray) -> pa.Array:
    return pa.Array.from_buffers(pa.binary(), len(length), [None, pa.py_buffer(np.r_[0, np.cumsum(length)].astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data))])


def named(points: DataFrame) -> DataFrame:
    """id, one, two, size: equal sets have equal names."""
    return points.where("id is not null and feat is not null").select("id", F.xxhash64("feat", F.lit(1)).alias("one"), F.xxhash64("feat", F.lit(2)).alias("two"), F.size("feat").alias("size"))


class Group:
    """The different sets of a group by the widths of their signatures, with their keys."""

    def __init__(self, table: pa.Table):
        one, two, size, ids = (table.column(c).to_numpy() for c in ("one", "two", "size", "id"))
        order = np.lexsort((ids, size, two, one))
        same = (np.diff(one[order]) == 0) & (np.diff(two[order]) == 0) & (np.diff(size[order]) == 0)
        starts = np.flatnonzero(np.r_[True, ~same])
        copies = np.diff(np.r_[starts, len(order)])
        first = order[starts]
        width = widths(size[first]) // 64
        by = np.argsort(width, kind="stable")
        self.rows, self.copies = first[by], copies[by]
        self.ids, self.size, self.width = ids[self.rows], size[self.rows].astype(np.int64), width[by]
        self.heavy = table.column("heavy").to_numpy()[self.rows]
        self.kinds, begin = np.unique(self.width, return_index=True)
        self.begin = begin.tolist()
        ends = [*self.begin[1:], len(self.rows)]
        self.sigs = []
        data, start = opened(table.column("sig"), "<u8")
        for w, i, j in zip(self.kinds.tolist(), self.begin, ends, strict=True):
            self.sigs.append(data[start[self.rows[i:j], None] + np.arange(w)])
        self.kind = np.searchsorted(self.kinds, self.width)
        data, start = opened(table.column("keys"), "<i8")
        self.stop = (np.diff(np.r_[start, len(data)])[0]) if len(start) else 0
        self.keys, self.start = data, start[self.rows]

    def met(self, tag: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Places of all pairs of different sets with the same key, about STEP at once."""
        key = self.keys[self.start + tag]
        order = np.argsort(key)
        key = key[order]
        starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]][: len(key)])
        last = np.repeat(np.r_[starts[1:], len(key)], np.diff(np.r_[starts, len(key)]))
        n = last - np.arange(len(key)) - 1
        cuts = np.cumsum(n) // STEP
        edges = [0, *(np.flatnonzero(np.diff(cuts)) + 1).tolist(), len(n)]
        for low, high in zip(edges[:-1], edges[1:], strict=True):
            some = n[low:high]
            x = np.repeat(np.arange(low, high), some)
            if len(x):
                y = x + 1 + np.arange(len(x)) - np.repeat(np.cumsum(some) - some, some)
                yield order[x], order[y]

    def met_by_set(self, tag: int) -> np.ndarray:
        """For each set how many points it has met, copies of its own not among them."""
        _, which = np.unique(self.keys[self.start + tag], return_inverse=True)
        return np.bincount(which, self.copies)[which].astype(np.int64) - self.copies

    def like(self, x: np.ndarray, y: np.ndarray, r: float) -> tuple[np.ndarray, np.ndarray]:
        """The pairs that sizes and signatures allow."""
        a, b = self.size[x], self.size[y]
        fit = (a * r <= b + 1e-9) & (b * r <= a + 1e-9)
        x, y = x[fit], y[fit]
        swap = self.kind[x] > self.kind[y]
        x, y = np.where(swap, y, x), np.where(swap, x, y)
        most = np.floor((self.size[x] + self.size[y]) * ((1 - r) / (1 + r)) + 1e-6)
        pair = self.kind[x] * len(self.kinds) + self.kind[y]
        keep = np.zeros(len(x), bool)
        for code in np.unique(pair).tolist():
            i, j = divmod(code, len(self.kinds))
            w, here = int(self.kinds[i]), np.flatnonzero(pair == code)
            for s in range(0, len(here), max(1, STEP // int(self.kinds[j]))):
                some = here[s : s + max(1, STEP // int(self.kinds[j]))]
                one, two = self.sigs[i][x[some] - self.begin[i]], self.sigs[j][y[some] - self.begin[j]]
                if i != j:
                    two = np.bitwise_xor.reduce(two.reshape(len(some), -1, w), axis=1)
                keep[some] = np.bitwise_count(one ^ two).sum(axis=1, dtype=np.int64) <= most[some]
        return x[keep], y[keep]


def opened(column: pa.ChunkedArray, kind: str) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of all rows of a binary column, and where those of each row begin."""
    whole = pa.concat_arrays(column.chunks)
    start = np.frombuffer(whole.buffers()[1], np.int32, len(whole) + 1, whole.offset * 4).astype(np.int64)
    data = np.frombuffer(whole.buffers()[2], kind, (start[-1] - start[0]) // 8, start[0])
    return data, (start[:-1] - start[0]) // 8


def dealt(points: DataFrame, family: HashFamily, seed: int, names: list[Name], k: int, tags: int, slices: int) -> DataFrame:
    """grp, id, one, two, size, sig, keys, heavy: each set once for every so many repetitions, or for a slice of the keys of each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = min(4096, max(1, 2_000_000 // max(1, len(names) * k)))
        for whole in batches:
            for at in range(0, whole.num_rows, step):
                batch = whole.slice(at, step)
                sets = Batch(batch.column(1), "sets")
                keys = family.keys(sets, seed, names, k)
                size = np.diff(sets.starts)
                plain = pa.record_batch([batch.column(0), batch.column(2), batch.column(3), pa.array(size.astype(np.int32)), signatures(sets.tokens, size), batch.column(4)], names=["id", "one", "two", "size", "sig", "heavy"])
                for number, first in enumerate(range(0, len(names), tags)):
                    some = np.ascontiguousarray(keys[:, first : first + tags])
                    part = pa.record_batch([pa.array(np.full(len(some), number, np.int32)), *plain.columns, binaries(some.view(np.uint8).reshape(-1), np.full(len(some), some.shape[1] * 8))], names=["grp", *plain.schema.names, "keys"])
                    if slices == 1:
                        yield part
                    else:
                        slot = number * slices + (some[:, 0].view(np.uint64) % np.uint64(slices)).astype(np.int32)
                        yield part.set_column(0, "grp", pa.array(slot.astype(np.int32)))

    heavy = F.col("heavy") if "heavy" in points.columns else F.lit(False)
    told = points.where("id is not null and feat is not null").select("id", "feat", F.xxhash64("feat", F.lit(1)), F.xxhash64("feat", F.lit(2)), heavy)
    return told.mapInArrow(run, "grp int, id long, one long, two long, size int, sig binary, heavy boolean, keys binary")


class Meetings:
    """Self-joins of sets under the keys of a plan; names are those of the sets' rows, written."""

    def __init__(self, points: DataFrame, at: Thresholds, family: HashFamily, seed: int, k: int):
        self.points, self.at, self.family, self.seed, self.k = points, at, family, seed, k
        self.spark: SparkSession = points.sparkSession
        names = written(named(points), "names")
        sig = F.greatest(F.lit(FLOOR), F.pow(F.lit(2.0), F.ceil(F.log2(4.0 * F.greatest("size", F.lit(1)))))) / 8
        told = names.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.avg(sig), F.lit(0)).alias("sig"), F.countDistinct("id").alias("ids")).first()
        self.n, self.each, self.unique = told.n, ROW + told.sig, told.n == told.ids
        reps = names.groupBy("one", "two", "size").agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("copies"))
        self.classes = written(names.join(reps, ["one", "two", "size"]).select("id", "rep", "copies", "size"), "classes")

    def sizes(self, number: int) -> tuple[int, int]:
        """Repetitions of a group, and slices of their keys."""
        room = GROUP / max(1, self.n)
        if room < self.each + 8:
            return 1, int(-(-self.n * (self.each + 8) // GROUP))
        return max(1, min(int((room - self.each) // 8), TAGS, -(-number // 8))), 1

    def passes(self, names: list[Name], reps: int) -> Iterator[list[Name]]:
        """Whole rounds, as many as a pass may shuffle."""
        tags, _ = self.sizes(len(names))
        rounds = max(1, int(PASS // max(1.0, self.n * reps * (8 + self.each / tags))))
        yield from (names[first : first + rounds * reps] for first in range(0, len(names), rounds * reps))

    def grouped(self, names: list[Name], compare, schema: str, points: DataFrame | None = None) -> DataFrame:
        tags, slices = self.sizes(len(names))
        rows = dealt(self.points if points is None else points, self.family, self.seed, names, self.k, tags, slices)
        return rows.repartition(max(16, -(-len(names) // tags) * slices), "grp").groupBy("grp").applyInArrow(compare, schema)

    def alike(self, names: list[Name], points: DataFrame | None = None, counted: bool = False) -> DataFrame:
        """a, b, n: classes that met under one of the names and that sizes and signatures allow, repeats included, with n null.
        With counted also rows with b null, where n is how many points a class has met, and all pairs that a class in a
        column heavy of the points has met, with n, how often."""
        r = self.at.r

        def compare(table: pa.Table) -> pa.Table:
            group = Group(table)
            del table
            n, found, crowd, held = len(group.ids), [np.zeros(0, np.int64)], [], 0
            seen = np.zeros(n, np.int64)
            for tag in range(group.stop):
                if counted:
                    seen += group.met_by_set(tag)
                for x, y in group.met(tag):
                    if counted and group.heavy.any():
                        some = group.heavy[x] | group.heavy[y]
                        crowd.append(np.minimum(x, y)[some] * n + np.maximum(x, y)[some])
                    x, y = group.like(x, y, r)
                    found.append(np.minimum(x, y) * n + np.maximum(x, y))
                    held += len(x)
                    if held > 4 * STEP:
                        found = [np.unique(np.concatenate(found))]
                        held = 0
            whole = np.unique(np.concatenate(found))
            often, times = np.unique(np.concatenate(crowd), return_counts=True) if crowd else (whole[:0], whole[:0])
            some = np.flatnonzero(seen)
            one, two = (np.concatenate([group.ids[v(whole)], group.ids[v(often)]]) for v in (lambda w: w // max(1, n), lambda w: w % max(1, n)))
            a = np.concatenate([np.minimum(one, two), group.ids[some]])
            b = pa.array(np.concatenate([np.maximum(one, two), some]), mask=np.arange(len(a)) >= len(one))
            return pa.table({"a": a, "b": b, "n": pa.array(np.concatenate([whole, times, seen[some]]), mask=np.arange(len(a)) < len(whole))})

        return self.grouped(names, compare, "a long, b long, n long", points)

    def measured(self, pairs: DataFrame) -> DataFrame:
        """a, b, value: the similarity of each of the pairs of classes, which come once each, from the whole sets."""
        cells = max(16, -(-self.n // CELL))
        lead = pairs.groupBy(F.col("b").alias("a")).agg(F.min("a").alias("least"))
        led = pairs.join(lead, "a", "left").select("a", "b", F.coalesce("least", "a").alias("lead"))
        led = written(led, "led")
        crowds = led.groupBy("lead").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > SHARE)
        share = F.pmod(F.xxhash64("a"), F.lit(1) + F.floor(F.coalesce("n", F.lit(0)) / SHARE))
        placed = written(led.join(crowds, "lead", "left").select(F.pmod(F.xxhash64("lead", share), F.lit(cells)).cast("int").alias("cell"), "a", "b"), "placed")
        wanted = placed.select(F.col("cell").alias("of"), F.col("a").alias("id")).union(placed.select("cell", "b")).distinct()
        data = self.points.where("feat is not null").select("id", "feat").join(wanted, "id").select("of", "id", "feat")
        ends = [f.repartition(cells, by).groupBy(by) for f, by in ((placed, "cell"), (data, "of"))]
        return ends[0].cogroup(ends[1]).applyInArrow(similarities, "a long, b long, value double")

    def told(self, pairs: DataFrame) -> DataFrame:
        """id_l, id_r, value: the near ones of pairs of classes."""
        return self.expanded(written(self.measured(pairs.distinct()).where(self.at.near(F.col("value"))), "values"))

    def expanded(self, values: DataFrame) -> DataFrame:
        """id_l, id_r, value of all near points from those of near classes, and of copies."""
        of = self.classes.select("id", "rep")
        between = values.join(of.toDF("x", "a"), "a").join(of.toDF("y", "b"), "b").select("x", "y", "value")
        within = of.toDF("x", "rep").join(of.toDF("y", "rep"), "rep").where("x < y").select("x", "y", F.lit(1.0).alias("value"))
        return between.union(within).select(F.least("x", "y").alias("id_l"), F.greatest("x", "y").alias("id_r"), "value")


def similarities(pairs: pa.Table, sets: pa.Table) -> pa.Table:
    a, b = pairs.column("a").to_numpy(), pairs.column("b").to_numpy()
    if not len(a):
        return pa.table({"a": a, "b": b, "value": np.zeros(0)})
    ids = sets.column("id").to_numpy()
    lists = pa.concat_arrays(sets.column("feat").chunks)
    start = lists.offsets.to_numpy().astype(np.int64)
    token = lists.values.to_numpy(zero_copy_only=False)[start[0] : start[-1]]
    start = start - start[0]
    size = np.diff(start)
    kinds, token = np.unique(token, return_inverse=True)
    by = np.argsort(ids)
    x, y = (by[np.searchsorted(ids[by], v)] for v in (a, b))
    order = np.argsort(x, kind="stable")
    common = np.zeros(len(x), np.int64)
    mark = np.zeros(len(kinds), bool)
    edges = [*np.flatnonzero(np.r_[True, np.diff(x[order]) != 0]).tolist(), len(order)]
    for first, last in zip(edges[:-1], edges[1:], strict=True):
        own = token[start[x[order[first]]] : start[x[order[first]] + 1]]
        mark[own] = True
        most = max(1, STEP // int(size[y[order[first:last]]].max(initial=1)))
        for s in range(first, last, most):
            some = order[s : min(s + most, last)]
            mine = size[y[some]]
            place = np.arange(mine.sum()) + np.repeat(start[y[some]] - (np.cumsum(mine) - mine), mine)
            which = np.repeat(np.arange(len(some)), mine)
            common[some] = np.bincount(which[mark[token[place]]], minlength=len(some))
        mark[own] = False
    return pa.table({"a": a, "b": b, "value": common / (size[x] + size[y] - common)})


def released(spark: SparkSession) -> None:
    """Lets Spark delete shuffles that no plan reads any more, before the next pass makes its own."""
    spark._jvm.System.gc()


def near_met_sets(points: DataFrame, at: Thresholds, family: HashFamily, seed: int, names: list[Name], k: int, reps: int) -> DataFrame | None:
    """id_l, id_r, value: the near pairs of sets that met in a bucket, empty sets and other copies among them; None if ids repeat."""
    join = Meetings(points, at, family, seed, k)
    if not join.unique:
        return None
    found = []
    for some in join.passes(names, reps):
        found.append(written(join.alike(some).select("a", "b"), "met"))
        released(join.spark)
    return join.told(reduce(DataFrame.union, found))


def near_met_capped(points: DataFrame, at: Thresholds, family: HashFamily, seed: int, rounds: list[list[Name]], k: int, batch: int, far_cap: float) -> DataFrame | None:
    """The rows of ``near_met_sets``, where a point leaves the rest of its round once it has met more than far_cap far
    points in batches of so many repetitions. A round where no point meets more than far_cap points at all is done at
    once; otherwise all that those heavy points meet is measured batch by batch, since nobody else can leave."""
    join = Meetings(points, at, family, seed, k)
    if not join.unique:
        return None
    copies = join.classes.where("id = rep").select("id", "copies")
    found = []
    for names in rounds:
        met = written(join.alike(names, counted=True), "met")
        heavy = written(met.where("b is null").groupBy("a").agg(F.sum("n").alias("n")).where(F.col("n") > far_cap).select("a"), "heavy")
        if heavy.isEmpty():
            found.append(met.where("n is null").select("a", "b"))
            released(join.spark)
            continue
        members = written(join.classes.join(heavy, F.col("rep") == F.col("a")).select("id", "rep"), "heavies")
        counts, out = None, None
        for first in range(0, len(names), batch):
            flags = members if out is None else members.join(out.select("rep"), "rep", "left_anti")
            here = points if out is None else points.join(members.join(out.select("rep"), "rep").select("id"), "id", "left_anti")
            here = here.join(flags.select("id", F.lit(True).alias("heavy")), "id", "left").withColumn("heavy", F.coalesce("heavy", F.lit(False)))
            met = written(join.alike(names[first : first + batch], here, True), "met")
            found.append(met.where("n is null").select("a", "b"))
            often = written(met.where("b is not null and n is not null").groupBy("a", "b").agg(F.sum("n").alias("n")), "often")
            far = written(join.measured(often.select("a", "b")).where(~at.close(F.col("value"))), "far").join(often, ["a", "b"])
            both = far.select(F.col("a").alias("rep"), F.col("b").alias("id"), "n").union(far.select("b", "a", "n"))
            now = both.join(copies, "id").groupBy("rep").agg(F.sum(F.col("n") * F.col("copies")).alias("n"))
            counts = written(now if counts is None else counts.union(now).groupBy("rep").agg(F.sum("n").alias("n")), "counters")
            out = counts.where(F.col("n") > far_cap)
            released(join.spark)
    return join.told(reduce(DataFrame.union, found))


def near_met_until(points: DataFrame, at: Thresholds, family: HashFamily, seed: int, rounds: list[list[Name]], k: int, enough) -> DataFrame | None:
    """The rows of ``near_met_sets`` of as many rounds as enough(functions so far, values, weight) wants: values has the near
    classes found (value, and weight, how many pairs of points they stand for), and so many pairs are of copies."""
    join = Meetings(points, at, family, seed, k)
    if not join.unique:
        return None
    copies = join.classes.where("id = rep").select("id", "copies")
    within = copies.agg(F.coalesce(F.sum(F.expr("copies * (copies - 1) div 2")), F.lit(0))).first()[0]
    seen = found = None
    functions = 0
    for names in rounds:
        new = join.alike(names).select("a", "b").distinct()
        now = written(join.measured(written(new if seen is None else new.join(seen, ["a", "b"], "left_anti"), "new")), "round")
        seen = now.select("a", "b") if seen is None else seen.union(now.select("a", "b"))
        some = now.where(at.near(F.col("value"))).join(copies.toDF("a", "of_a"), "a").join(copies.toDF("b", "of_b"), "b")
        some = written(some.select("a", "b", "value", (F.col("of_a") * F.col("of_b")).alias("weight")), "found")
        found = some if found is None else found.union(some)
        functions += len(names)
        released(join.spark)
        if enough(functions, found, within):
            break
    return join.expanded(found.select("a", "b", "value"))
