"""Mixing sources to target weights, with DataFrame functions only.

Tokens per source are aggregated once; a source's repetition rate is its target
over its size. A document is taken floor(rate) times, and once more when a draw
seeded by its id falls below the fraction. The rate depends on the source and
the draw on the id, so texts are neither shuffled nor measured again.

Defined cases: a null or empty text has size 0 and is taken like any other; a
null source is a source, sorted last; rows that repeat a doc_id share its draw;
a source of size 0 has target 0 and none of its documents is taken; an empty
table gives an empty result. Extra columns pass through ``mix`` untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import fresh, unit_draw, words, written

#: Weights by a source's place in code-point order, repeating; no target is above MOST times its source.
WEIGHTS, MOST, SEED = (1, 2, 3), 3, 20


def measured(docs: DataFrame) -> DataFrame:
    """doc_id, source and size in words, written once: all later steps read these narrow rows."""
    return written(docs.select("doc_id", "source", F.size(words(F.col("text"))).cast("long").alias("size")), "sizes")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = 1.0, most: int = MOST) -> DataFrame:
    """source, source_size, weight, target and rate for each source.

    Targets are weight shares of ``share`` times all sizes. A target stops at
    ``most`` times its source's size and the excess goes to the others by weight.
    Sources in order of most*size/weight fill up one after another, so the level
    at which no other is above its limit follows from two running sums; the
    windows below see one row per source, not per document.
    """
    by_source = sizes.groupBy("source").agg(F.coalesce(F.sum("size"), F.lit(0)).alias("source_size"))
    place = Window.orderBy(F.col("source").asc_nulls_last())
    everything = Window.partitionBy()
    fill = Window.orderBy("full_at", F.col("source").asc_nulls_last())
    before = fill.rowsBetween(Window.unboundedPreceding, -1)
    pick = F.element_at(F.array(*map(F.lit, weights)), ((F.row_number().over(place) - 1) % len(weights) + 1).cast("int"))
    ranked = (
        by_source.withColumn("weight", pick)
        .withColumn("limit", most * F.col("source_size"))
        .withColumn("full_at", F.col("limit") / F.col("weight"))
        .withColumn("wanted", F.lit(float(share)) * F.sum("source_size").over(everything))
        .withColumn("level", (F.col("wanted") - F.coalesce(F.sum("limit").over(before), F.lit(0))) / (F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0))))
        .withColumn("place", F.row_number().over(fill))
        .withColumn("open", F.min(F.when(F.col("full_at") >= F.col("level"), F.struct("place", "level"))).over(everything))
    )
    # where even all limits together stay below what is wanted, every target is its limit
    target = F.when(F.col("open").isNull() | (F.col("place") < F.col("open.place")), F.col("limit").cast("double")).otherwise(F.least(F.col("limit").cast("double"), F.col("weight") * F.col("open.level")))
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    return ranked.withColumn("target", target).withColumn("rate", rate).select("source", "source_size", "weight", "target", "rate")


def copies(rate: Column, doc_id: Column, seed: int = SEED) -> Column:
    """How often a document is taken: floor(rate), and one more by its own draw."""
    whole = F.floor(rate)
    return (whole + (unit_draw(F.lit(str(seed)), doc_id) < rate - whole).cast("long")).cast("int")


def with_rates(docs: DataFrame, targets: DataFrame) -> DataFrame:
    """docs with the columns of their source's target. The targets are a written
    table of one row per source, so the planner knows its size: it broadcasts a
    small one and else joins by sort and merge, where a hot source is split."""
    wanted = written(targets, "targets")
    for name, own in zip(wanted.columns, fresh(docs, *[f"mix_{c}" for c in wanted.columns]), strict=True):
        wanted = wanted.withColumnRenamed(name, own)
    return docs.join(wanted, docs["source"].eqNullSafe(wanted[wanted.columns[0]]), "left")


def mix(docs: DataFrame, seed: int = SEED, **how) -> DataFrame:
    """docs with each row repeated as often as the mix takes it; same columns."""
    rated = with_rates(docs, source_targets(measured(docs), **how))
    rate = rated[rated.columns[-1]]
    times = F.sequence(F.lit(1), copies(rate, docs["doc_id"], seed))
    (copy,) = fresh(rated, "copy")
    return rated.where(copies(rate, docs["doc_id"], seed) > 0).withColumn(copy, F.explode(times)).select(*[docs[c] for c in docs.columns])


def mix_plan(docs: DataFrame, seed: int = SEED, **how) -> DataFrame:
    """What the mix does with each document: size, source_size, target, copies and taken words."""
    sizes = measured(docs)
    rated = with_rates(sizes, source_targets(sizes, **how))
    times = copies(F.col("mix_rate"), F.col("doc_id"), seed)
    return rated.select("doc_id", "size", F.col("mix_source_size").alias("source_size"), F.col("mix_target").alias("target"), (F.col("size") * times).alias("taken"), times.alias("copies"))
