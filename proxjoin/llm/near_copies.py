"""Near-dedup by SimHash, checked and completed by the exact Jaccard similarity of word shingles.

Two texts are near copies if the sets of their shingles of SHINGLE words have a
similarity of SIMILARITY or more; a component of such links keeps one row. First
SimHash: sets become fingerprints, pigeonring chains find those that differ in up
to BUDGET bits (simhash.cell_links), and whole sets are compared for these. Pairs
that hold put sets into classes.

Fingerprints of similar sets may differ in more bits, as chance has it, so pairs of
sets of different classes are looked for without a draw, and none is missed: in
one order of all shingles, sets that similar share one of the first shingles of
each, its prefix. The order puts shingles that many texts share last, by SLOTS
counters of all shingles, a table whose size does not depend on the data; what it
tells apart changes the work, not the result.

Prefix shingles are dealt into buckets as packed arrays, and those of one set go
there. Sets of different classes that meet under a shingle of up to CROWD sets are
paired, and each pair is checked once: the pairs of a component of candidates stand
together, at most SHARE of them, so that a set travels once for many pairs. All sets
under larger shingles of several classes are compared in cells: classes of like
sizes, cut into squares of CELL sets, counted by a local index. So crowds make no
rows for their pairs, but the work on them grows with their square.

Defined cases: words are parted by ASCII white space and compared in ASCII lower
case; a text of fewer words than a shingle is one shingle, and all texts without
words are alike; a null text is the empty text. Shingles compare by 64 hash bits.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import simhash
from .blobs import BASES, SLOTS, buckets_for, by_bytes, opened, rows, runs, slots_counted, spans_hashed, squeezed, word_hashes
from .common import discarded, one_of_each, text_key, written
from .simhash import components

SHINGLE, SIMILARITY, CROWD, CELL = 5, Fraction(4, 5), 64, 2048
#: Bits by which fingerprints of candidates may differ: the most under which two segments of eight may differ in two bits only.
BUDGET = 11
#: Bytes of text taken together, bytes of text for a bucket, pairs checked together.
STEP, EACH, SHARE = 4 << 20, 8 << 20, 1 << 16


def shingle_sets(texts: list[str | None], shingle: int) -> list[np.ndarray]:
    """The distinct shingles of each text by their hashes, in ascending order."""
    hashes, counts = word_hashes([(t or "").encode().lower().decode() for t in texts])
    stop = np.cumsum(counts)
    out = []
    number = np.where(counts > 0, np.maximum(counts - shingle + 1, 1), 0)
    at = np.arange(number.sum()) + np.repeat(stop - counts - (np.cumsum(number) - number), number)
    key = spans_hashed(hashes, at, np.minimum(at + shingle, np.repeat(stop, number)), BASES[1]) if len(at) else np.zeros(0, np.uint64)
    first = 0
    for n in number.tolist():
        out.append(np.unique(key[first : first + n]) if n else np.zeros(1, np.uint64))
        first += n
    return out


def steps(batches: Iterator[pa.RecordBatch], shingle: int) -> Iterator[tuple[pa.RecordBatch, list[np.ndarray]]]:
    """Parts of the batches, whose last column is the text, with their sets."""
    for part in (part for batch in batches for part in by_bytes(batch, STEP)):
        yield part, shingle_sets(part.column(part.num_columns - 1).to_pylist(), shingle)


def name_of(shingles: np.ndarray) -> bytes:
    return hashlib.md5(shingles.astype("<u8").tobytes()).digest()


def slot_of(shingles: np.ndarray) -> np.ndarray:
    return (shingles >> np.uint64(64 - SLOTS)).astype(np.int64)


def commonness(docs: DataFrame, shingle: int) -> np.ndarray:
    """How many texts have a shingle in each slot."""
    return slots_counted(docs.select("text"), lambda batch: (slot_of(np.concatenate(sets)) for _, sets in steps(iter([batch]), shingle)))


def key_slots(keys: pa.Array) -> np.ndarray:
    """Slots of text keys, by their first eight bytes."""
    return slot_of(np.frombuffer(b"".join(k[:8] for k in keys.to_pylist()), ">u8"))


def prefix(shingles: np.ndarray, counts: np.ndarray, least: Fraction) -> np.ndarray:
    """The first shingles of a set, so many that any set as similar as ``least`` has one of them among its own first ones."""
    n = len(shingles) - math.ceil(least * len(shingles)) + 1
    return shingles[np.argsort(counts[slot_of(shingles)], kind="stable")[:n]]


def shared(docs: DataFrame, shingle: int, least: Fraction, buckets: int, counts: Broadcast) -> DataFrame:
    """token, node, n: prefix shingles of n > 1 sets, with each of these."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, sets in steps(batches, shingle):
            names = np.frombuffer(b"".join(map(name_of, sets)), "<u8").reshape(-1, 2)
            firsts = [prefix(s, counts.value, least) for s in sets]
            token, which = np.concatenate(firsts), np.repeat(np.arange(len(sets)), [len(x) for x in firsts])
            bucket = (token % np.uint64(buckets)).astype(np.int64)
            order = np.argsort(bucket, kind="stable")
            out = []
            for a, b in runs(bucket[order]):
                some = order[a:b]
                used, local = np.unique(which[some], return_inverse=True)
                out.append((int(bucket[some[0]]), squeezed(token[some], local.astype("<u4"), names[used, 0], names[used, 1])))
            yield from rows([("bucket", pa.int64()), ("data", pa.binary())], *map(list, zip(*out, strict=True))).to_batches()

    def meet(table: pa.Table) -> pa.Table:
        parts = [opened(d.as_py()) for d in table.column("data")]
        token = np.concatenate([p[0] for p in parts])
        one, two = (np.concatenate([p[k][p[1]] for p in parts]) for k in (2, 3))
        order = np.argsort(token)
        same = np.diff(token[order]) == 0
        met = order[np.r_[False, same] | np.r_[same, False]]
        met = met[np.lexsort((two[met], one[met], token[met]))]
        token, one, two = token[met], one[met], two[met]
        own = np.r_[True, (np.diff(token) != 0) | (np.diff(one) != 0) | (np.diff(two) != 0)][: len(token)]  # equal sets are one node
        token, names = token[own], np.stack([one[own], two[own]], 1).astype("<u8")
        _, which, n = np.unique(token, return_inverse=True, return_counts=True)
        n = n[which]
        token, names, n = token[n > 1], names[n > 1].tobytes(), n[n > 1]
        return pa.table({"token": pa.array(token.view(np.int64)), "node": pa.array([names[k : k + 16] for k in range(0, len(names), 16)], pa.binary()), "n": pa.array(n.astype(np.int64))})

    dealt = docs.select("text").mapInArrow(run, "bucket long, data binary")
    return dealt.groupBy("bucket").applyInArrow(meet, "token long, node binary, n long")


def alike(common: np.ndarray | int, a: np.ndarray | int, b: np.ndarray | int, least: Fraction):
    return common * (least.numerator + least.denominator) >= least.numerator * (a + b)


def dealt(pairs: DataFrame, share: int = SHARE) -> DataFrame:
    """team, a, b: the pairs of a component of pairs as one team, or as teams of about ``share``."""
    labels = components(pairs)
    placed = pairs.join(labels.withColumnRenamed("node", "a"), "a")
    cut = placed.groupBy("label").agg(F.ceil(F.count(F.lit(1)) / F.lit(share)).alias("cut"))
    return placed.join(cut, "label").select(F.xxhash64("label", F.pmod(F.xxhash64("a"), F.col("cut"))).alias("team"), "a", "b")


def checked(teams: DataFrame, sets: DataFrame, least: Fraction, buckets: int) -> DataFrame:
    """The pairs whose sets are alike; sets has team, node, data."""

    def compare(pairs: pa.Table, sets: pa.Table) -> pa.Table:
        found = {n: np.frombuffer(d.as_buffer(), "<u8") for n, d in zip(sets.column("node").to_pylist(), sets.column("data"), strict=True)}
        keep = []
        for a, b in zip(pairs.column("a").to_pylist(), pairs.column("b").to_pylist(), strict=True):
            x, y = found[a], found[b]
            keep.append(bool(alike(len(np.intersect1d(x, y, assume_unique=True)), len(x), len(y), least)))
        return pairs.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    bucket = F.pmod("team", F.lit(buckets)).alias("bucket")
    ends = [f.repartition(buckets, "bucket").groupBy("bucket") for f in (teams.select(bucket, "a", "b"), sets.select(bucket, "node", "data"))]
    return ends[0].cogroup(ends[1]).applyInArrow(compare, "a binary, b binary")


def width(least: Fraction) -> float:
    """Sizes of sets that are alike lie in one class of this width of their logarithms, or in two that follow each other."""
    return math.log(1.01 / float(least))


def in_cells(sets: DataFrame, least: Fraction, cell: int = CELL) -> DataFrame:
    """a, b: links that join the classes of the sets (node, class, size, data) as all links do, found by comparing all of them with like sizes."""
    level = F.floor(F.log(F.col("size")) / F.lit(width(least)))
    placed = sets.select("node", "class", "data", F.explode(F.array(level, level - 1)).alias("level"))
    sizes = placed.groupBy("level").agg(F.ceil(F.count(F.lit(1)) / F.lit(cell)).cast("int").alias("cut"))
    part = placed.join(F.broadcast(sizes), "level").withColumn("part", F.pmod(F.xxhash64("node"), F.col("cut")).cast("int"))
    spread = part.select("level", "part", "node", "class", "data", F.explode(F.sequence(F.lit(0), F.col("cut") - 1)).alias("other"))
    cells = spread.select("level", F.least("part", "other").alias("low"), F.greatest("part", "other").alias("high"), "part", "node", "class", "data")

    def compare(table: pa.Table) -> pa.Table:
        names = table.column("node").to_pylist()
        part = table.column("part").to_numpy()
        sets_ = [np.frombuffer(v.as_buffer(), "<u8") for c in table.column("data").chunks for v in c]
        size = np.array([len(s) for s in sets_])
        number = np.repeat(np.arange(len(sets_)), size)
        _, local = np.unique(np.concatenate(sets_), return_inverse=True)
        order = np.argsort(local, kind="stable")
        holders, begin = number[order], np.searchsorted(local[order], np.arange(local.max() + 2))
        known: dict[bytes, int] = {}
        group = np.array([known.setdefault(c, len(known)) for c in table.column("class").to_pylist()])  # those linked so far share a number
        stop = np.cumsum(size)
        links, two = [], len(np.unique(part)) > 1
        for k in range(len(sets_)):
            own = local[stop[k] - size[k] : stop[k]]
            own = own[begin[own + 1] - begin[own] > 1]
            if not len(own):
                continue
            common = np.bincount(np.concatenate([holders[begin[t] : begin[t + 1]] for t in own.tolist()]), minlength=len(sets_))
            near = np.flatnonzero(alike(common, size, size[k], least) & (common > 0) & (group != group[k]))
            if two:
                near = near[part[near] != part[k]]
            for j in near.tolist():
                if group[j] != group[k]:
                    links.append((names[j], names[k]))
                    low, high = sorted((group[j], group[k]))
                    group[group == high] = low
        a, b = [min(p) for p in links], [max(p) for p in links]
        return pa.table({"a": pa.array(a, pa.binary()), "b": pa.array(b, pa.binary())})

    return cells.groupBy("level", "low", "high").applyInArrow(compare, "a binary, b binary")


def close_pairs(marks: DataFrame, least: Fraction, budget: int = BUDGET) -> DataFrame:
    """a, b with a < b: nodes of marks (node, size, bits) with one fingerprint, or with two that pigeonring chains link within budget."""
    nodes = marks.select("node", "size", "bits").distinct()
    firsts = written(nodes.groupBy("bits").agg(F.min("node").alias("first")), "firsts")
    close = simhash.cell_links(nodes, budget, width(least))
    for end in "ab":
        close = close.join(firsts.select(F.col("bits").alias(end), F.col("first").alias(f"first_{end}")), end)
    equal = nodes.join(firsts, "bits").select(F.col("first").alias("first_a"), F.col("node").alias("first_b"))
    ends = F.least("first_a", "first_b").alias("a"), F.greatest("first_a", "first_b").alias("b")
    return close.select(*ends).union(equal.select(*ends)).where("a < b").distinct()


def ends_of(teams: DataFrame) -> DataFrame:
    return teams.select("team", F.col("a").alias("node")).union(teams.select("team", "b")).distinct()


def whole_sets(keyed: DataFrame, marks: DataFrame, members: DataFrame, shingle: int) -> DataFrame:
    """members, which have a node, with the size and data of its set. Texts stay where they are: slots of the keys
    of fixed number tell most of those that aren't needed."""

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The sets of the rows whose key may be wanted."""
        wanted = (batch.filter(pa.array(slots.value[key_slots(batch.column(0))])) for batch in batches)
        for part, sets in steps((batch for batch in wanted if batch.num_rows), shingle):
            yield pa.record_batch([part.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array([s.astype("<u8").tobytes() for s in sets], pa.binary())], names=["key", "size", "data"])

    named = written(members.join(marks.groupBy("node").agg(F.min("key").alias("key")), "node"), "named")
    slots = keyed.sparkSession.sparkContext.broadcast(slots_counted(named.select("key"), lambda batch: iter([key_slots(batch.column(0))])) > 0)
    found = keyed.select("key", "text").mapInArrow(whole, "key binary, size long, data binary").groupBy("key").agg(F.first("size").alias("size"), F.first("data").alias("data"))
    sets = written(found.join(named, "key").drop("key"), "sets", "uncompressed")
    slots.destroy()
    discarded(named)
    return sets


def tasks_for(sets: DataFrame) -> int:
    return max(16, -(-(sets.agg(F.sum(F.octet_length("data"))).first()[0] or 0) // EACH))


def near_rows(docs: DataFrame, shingle: int = SHINGLE, least: Fraction = SIMILARITY, crowd: int = CROWD, cell: int = CELL, budget: int = BUDGET) -> DataFrame:
    """doc_id, key (of the text), label (of the component) of every row."""
    marks_type = "doc_id long, key binary, node binary, size long, bits long"

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, sets in steps(batches, shingle):
            sizes, bits = pa.array([len(s) for s in sets], pa.int64()), pa.array(map(simhash.majority, sets), pa.int64())
            yield pa.record_batch([part.column(0), part.column(1), pa.array(map(name_of, sets), pa.binary()), sizes, bits], names=["doc_id", "key", "node", "size", "bits"])

    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key(F.col("text")).alias("key"), "text")
    marks = written(keyed.mapInArrow(mark, marks_type), "marks")
    close = written(close_pairs(marks, least, budget), "close")
    teams = close.withColumn("team", F.xxhash64("a", "b"))  # there are no more pairs than nodes, so each travels alone
    sets = whole_sets(keyed, marks, ends_of(teams), shingle)
    marked = written(checked(teams, sets, least, tasks_for(sets)), "marked")
    discarded(close, sets)
    classes = components(marked)

    counts = docs.sparkSession.sparkContext.broadcast(commonness(docs, shingle))
    met = written(shared(docs, shingle, least, buckets_for(docs, EACH), counts), "met")
    counts.destroy()
    sizes = met.select("node").distinct().join(marks.select("node", "size").distinct(), "node")
    sizes = written(sizes.join(classes, "node", "left").select("node", "size", F.coalesce("label", "node").alias("class")), "sizes")
    few = met.where(F.col("n") <= crowd).join(sizes, "node").select("token", "node", "size", "class")
    ends = [few.select("token", *[F.col(x).alias(f"{x}_{c}") for x in ("size", "class")], F.col("node").alias(c)) for c in "ab"]
    like = F.least("size_a", "size_b") * least.denominator >= F.greatest("size_a", "size_b") * least.numerator
    # what follows one of the two prefixes can be common at most; pairs under larger shingles are compared in cells, so their count may be too low
    rest = F.ceil(F.greatest("size_a", "size_b") * least.numerator / least.denominator) - 1
    enough = alike(F.col("met") + rest, F.col("size_a"), F.col("size_b"), least)
    apart = ends[0].join(ends[1], "token").where(F.col("a") < F.col("b")).where("class_a != class_b").where(like)
    pairs = written(apart.groupBy("a", "b", "size_a", "size_b").agg(F.count(F.lit(1)).alias("met")).where(enough).select("a", "b"), "pairs")
    teams = written(dealt(pairs), "teams")
    many = met.where(F.col("n") > crowd).join(sizes, "node").select("token", "node", "class")
    mixed = many.groupBy("token").agg(F.min("class").alias("low"), F.max("class").alias("high")).where("low != high").select("token")
    crowded = written(many.join(mixed, "token", "left_semi").select("node", "class").distinct(), "crowded")
    members = ends_of(teams).withColumn("class", F.lit(None).cast("binary")).union(crowded.select(F.lit(None).cast("long"), "node", "class"))
    sets = whole_sets(keyed, marks, members, shingle)
    alone = checked(teams, sets.where("team is not null"), least, tasks_for(sets))
    others = written(alone.union(in_cells(sets.where("team is null").drop("team"), least, cell)), "rest")
    discarded(met, sizes, pairs, teams, crowded, sets)
    # classes stand for their sets, so chains within them are not followed again
    for end in "ab":
        others = others.join(classes.select(F.col("node").alias(end), F.col("label").alias(f"class_{end}")), end, "left")
    ends = [F.coalesce(f"class_{end}", end) for end in "ab"]
    labels = components(others.select(F.least(*ends).alias("a"), F.greatest(*ends).alias("b")).where("a < b"))
    placed = marks.join(classes, "node", "left").select("doc_id", "key", F.coalesce("label", "node").alias("node"))
    return placed.join(labels, "node", "left").select("doc_id", "key", F.coalesce("label", "node").alias("label"))


def near_dedup(docs: DataFrame, shingle: int = SHINGLE, least: Fraction = SIMILARITY) -> DataFrame:
    """docs with one row of each component only, the one with the smallest doc_id; same columns."""
    return one_of_each(docs, written(near_rows(docs, shingle, least), "near"))
