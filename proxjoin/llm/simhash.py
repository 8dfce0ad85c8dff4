"""SimHash near-dedup with pigeonring filtering.

Texts become 64-bit fingerprints of their word shingles, and equal fingerprints
one node. A fingerprint is a ring of segments. If two differ in at most two
bits, a chain of consecutive segments exists on the ring whose differences, from
its start on, never exceed the share of the budget due to its length: none in
the first half, one before the last segment, two at most in all. So nodes meet
by the key of each first half, candidates must keep the whole chain of budgets
at the segment where they met, and the full Hamming check comes last.

Keys that up to CROWD nodes share are joined with themselves. Nodes under any
larger key are linked without their pairs, and exactly: each is written under
itself and its 64 one-bit neighbours, and all nodes under one such word, being
within two bits of each other, are linked to the smallest of them. Two nodes
within two bits always share a word, so no link is lost.

Under a wider budget keys are short and many nodes share one. So cell_links looks
for the pairs in cells of CELL x CELL fingerprints, within a task: eight segments
of eight bits, the first two of a chain as the key, under which nodes meet that
the chain's budgets allow there, then the whole chain and the Hamming check. It
gives a forest of links, close ones first, so crowds make no rows for their pairs;
the work on a cell is fixed, and cells grow in number with the square of the nodes.

Defined cases: a null text is the empty text; a text without words has the
fingerprint zero and is linked like any other; a null doc_id counts only where a
component has no other; rows that repeat a doc_id have a row each; near_dedup decides by row (one_of_each); an empty
table gives an empty result. Extra columns are ignored, or kept by near_dedup.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import one_of_each, text_key, written

SHINGLE, BITS, SEED, CROWD = 3, 2, 42, 64
#: Fingerprints of one part of a cell, and pairs looked at together there.
CELL, STEP = 1 << 14, 1 << 18


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    """The bits set in over half of the hashes of all shingles, repeats included."""
    from xxhash import xxh64_intdigest

    w = (text or "").encode().lower().split()
    if not w:
        return 0
    shingles = map(b" ".join, zip(*[w[k:] for k in range(shingle)], strict=False)) if len(w) >= shingle else iter([b" ".join(w)])
    count = max(len(w) - shingle + 1, 1)
    return majority(np.fromiter(map(xxh64_intdigest, shingles, repeat(SEED)), np.uint64, count))


def majority(hashes: np.ndarray) -> int:
    """The bits set in over half of the hashes, as a signed 64-bit integer."""
    ones = np.zeros(64, np.int64)
    for k in range(0, len(hashes), 16_384):
        ones += np.unpackbits(hashes[k : k + 16_384].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<i8")[0])


def fingerprints(docs: DataFrame, shingle: int = SHINGLE, *more: Column) -> DataFrame:
    """doc_id, more, bits: the fingerprint of every whole text as a signed 64-bit integer."""
    read = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *more, "text")
    given = read.columns[:-1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = (text.as_py() for text in batch.column(len(given)))  # one at a time in Python
            yield pa.record_batch([*batch.columns[:-1], pa.array([fingerprint(t, shingle) for t in texts], pa.int64())], names=[*given, "bits"])

    return read.mapInArrow(run, ", ".join([f"{c} {t}" for c, t in read.dtypes[:-1]] + ["bits long"]))


def turned(bits: Column, by: Column) -> Column:
    """bits rotated right; Java takes shifts modulo 64, so no turn at all works too."""
    call = lambda f, n: F.call_function(f, bits, n)
    return call("shiftrightunsigned", by).bitwiseOR(call("shiftleft", 64 - by))


def segments_for(nodes: int) -> int:
    """More and narrower segments make longer keys, 32 - 64 / segments bits: about as many as nodes need."""
    return 8 if nodes < 1 << 24 else 16 if nodes < 1 << 28 else 32


def links(nodes: DataFrame, segments: int, crowd: int = CROWD) -> DataFrame:
    """a, b with a < b: pairs of nodes whose links give the components of all links."""
    width, half = 64 // segments, segments // BITS - 1
    mask = lambda n: (1 << n * width) - 1
    place = F.explode(F.array(*[F.lit(k * width) for k in range(segments)])).alias("at")
    keyed = nodes.select("bits", place).withColumn("key", turned(F.col("bits"), F.col("at")).bitwiseAND(F.lit(mask(half))))
    shared = keyed.groupBy("at", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    met = written(keyed.join(shared, ["at", "key"]), "met")
    few = met.where(F.col("n") <= crowd).select("at", "key", "bits")
    pairs = few.withColumnRenamed("bits", "a").join(few.withColumnRenamed("bits", "b"), ["at", "key"]).where("a < b")
    apart = F.col("a").bitwiseXOR(F.col("b"))
    chain = [F.bit_count(turned(apart, F.col("at")).bitwiseAND(F.lit(mask(n)))) <= n * BITS // segments for n in range(half + 1, segments)]
    for budget in chain:
        pairs = pairs.where(budget)
    close = pairs.where(F.bit_count(apart) <= BITS).select("a", "b")
    crowded = met.where(F.col("n") > crowd).select("bits").distinct()
    flips = F.array(F.lit(0).cast("long"), *[F.lit((1 << k) - (1 << 64 if k == 63 else 0)) for k in range(64)])
    words = crowded.select("bits", F.explode(flips).alias("flip")).select("bits", F.col("bits").bitwiseXOR(F.col("flip")).alias("word"))
    hubs = words.groupBy("word").agg(F.min("bits").alias("hub"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
    stars = words.join(hubs, "word").where("bits > hub").select(F.col("hub").alias("a"), F.col("bits").alias("b"))
    return close.union(stars).distinct()


def chained(bits: np.ndarray, budget: int, part: np.ndarray, group: np.ndarray, step: int = STEP) -> list[tuple[int, int]]:
    """Places of links within budget that join the groups of all such links; group is changed. Only links between two parts, if there are two."""
    allowed = [n * budget // 8 for n in range(9)]
    words = np.arange(1 << 16, dtype=np.uint64)
    flips = np.flatnonzero((np.bitwise_count(words & np.uint64(255)) <= allowed[1]) & (np.bitwise_count(words) <= allowed[2]))
    across, places, out = len(part) > 0 and part.min() < part.max(), np.arange(len(bits)), []
    for at in range(0, 64, 8):
        ring = bits >> np.uint64(at) | bits << np.uint64(64 - at) if at else bits
        order = np.argsort(ring & np.uint64(0xFFFF), kind="stable")
        ring = ring[order]
        key = (ring & np.uint64(0xFFFF)).astype(np.int64)
        begin = np.searchsorted(key, np.arange((1 << 16) + 1))
        for flip in flips.tolist():
            low = np.maximum(begin[key ^ flip], places + 1)  # each pair from its first place
            n = np.maximum(begin[(key ^ flip) + 1] - low, 0)
            some = np.flatnonzero(n)
            share = np.cumsum(n[some]) // step
            for first, last in zip(*(np.searchsorted(share, np.unique(share), side) for side in ("left", "right")), strict=True):
                own = some[first:last]
                a = np.repeat(own, n[own])
                b = np.arange(len(a)) + np.repeat(low[own] - np.cumsum(n[own]) + n[own], n[own])
                keep = group[order[a]] != group[order[b]]
                if across:
                    keep &= part[order[a]] != part[order[b]]
                a, b = a[keep], b[keep]
                for k in range(3, 9):
                    near = np.bitwise_count((ring[a] ^ ring[b]) & np.uint64((1 << 8 * k) - 1)) <= allowed[k]
                    a, b = a[near], b[near]
                for x, y in zip(order[a].tolist(), order[b].tolist(), strict=True):
                    if group[x] != group[y]:
                        out.append((x, y))
                        group[group == group[y]] = group[x]
    return out


def cell_links(nodes: DataFrame, budget: int, wide: float, cell: int = CELL) -> DataFrame:
    """a, b with a < b: links of fingerprints within budget whose components are those of all such links of like sizes.

    nodes has bits and size; sizes are alike if their logarithms differ by less than wide.
    """
    level = F.floor(F.log(F.col("size")) / F.lit(wide))
    placed = nodes.select("bits", F.explode(F.array(level, level - 1)).alias("level")).distinct()
    sizes = placed.groupBy("level").agg(F.ceil(F.count(F.lit(1)) / F.lit(cell)).cast("int").alias("cut"))
    part = placed.join(F.broadcast(sizes), "level").withColumn("part", F.pmod(F.xxhash64("bits"), F.col("cut")).cast("int"))
    packed = part.groupBy("level", "part", "cut").agg(F.collect_list("bits").alias("bits"))
    spread = packed.select("level", "part", "bits", F.explode(F.sequence(F.lit(0), F.col("cut") - 1)).alias("other"))
    cells = spread.select("level", F.least("part", "other").alias("low"), F.greatest("part", "other").alias("high"), "part", "bits")

    def search(table: pa.Table) -> pa.Table:
        lists = [np.asarray(v.values).view(np.uint64) for c in table.column("bits").chunks for v in c]
        bits, part = np.concatenate(lists), np.repeat(table.column("part").to_numpy(), [len(x) for x in lists])
        group = np.arange(len(bits))
        found = [link for some in sorted({budget // 4, budget // 2, budget}) for link in chained(bits, some, part, group)]
        ends = bits.view(np.int64)[np.array(found, np.int64).reshape(-1, 2)]
        return pa.table({"a": ends.min(axis=1), "b": ends.max(axis=1)})

    return cells.groupBy("level", "low", "high").applyInArrow(search, "a long, b long").distinct()


def components(edges: DataFrame) -> DataFrame:
    """node, label: the smallest node of its component for each node that has an edge.

    Each round takes the smallest label among neighbours and then its label's
    label, so long chains halve; a round is a written table, and the driver sees
    one count of each.
    """
    both = written(edges.select(F.col("a").alias("node"), F.col("b").alias("other")).union(edges.select("b", "a")), "edges")
    now = written(both.groupBy("node").agg(F.least("node", F.min("other")).alias("label")), "labels")
    while True:
        around = both.join(now.select(F.col("node").alias("other"), "label"), "other").groupBy("node").agg(F.min("label").alias("near"))
        hooked = now.join(around, "node").select("node", F.col("label").alias("was"), F.least("label", "near").alias("label"))
        above = now.select(F.col("node").alias("label"), F.col("label").alias("over"))
        now = written(hooked.join(above, "label").select("node", F.least("label", "over").alias("label"), (F.least("label", "over") < F.col("was")).alias("moved")), "labels")
        if now.where("moved").isEmpty():
            return now.drop("moved")
        now = now.drop("moved")


def near_groups(docs: DataFrame, shingle: int = SHINGLE, crowd: int = CROWD, segments: int | None = None) -> DataFrame:
    """doc_id, bits, component_id (the smallest doc_id reachable by links) of every row."""
    marked = written(fingerprints(docs, shingle), "fingerprints")
    nodes = written(marked.groupBy("bits").agg(F.min("doc_id").alias("first")), "nodes")
    found = links(nodes, segments or segments_for(nodes.count()), crowd)
    labels = components(found)
    linked = nodes.join(labels.withColumnRenamed("node", "bits"), "bits")
    ids = linked.join(linked.groupBy("label").agg(F.min("first").alias("lowest")), "label").select("bits", "lowest")
    whole = written(nodes.join(ids, "bits", "left").select("bits", F.least("first", "lowest").alias("component_id")), "components")
    return marked.join(whole, "bits").select("doc_id", "bits", "component_id")


def near_rows(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """doc_id, key (of the text), label (of the component) of every row."""
    marked = written(fingerprints(docs, shingle, text_key(F.col("text")).alias("key")), "fingerprints")
    nodes = written(marked.select("bits").distinct(), "nodes")
    labels = components(links(nodes, segments_for(nodes.count()))).withColumnRenamed("node", "bits")
    return marked.join(labels, "bits", "left").select("doc_id", "key", F.coalesce("label", "bits").alias("label"))


def near_dedup(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """docs with one row of each component only, the one with the smallest doc_id; same columns."""
    return one_of_each(docs, written(near_rows(docs, shingle), "near"))
