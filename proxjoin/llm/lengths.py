"""Token counts: the exact histogram of encoded lengths, and what its suffix sums answer.

Each document is encoded once and leaves as a count of its length, combined
within its batch. Sums over all longer documents run in two steps, within blocks
of lengths and over blocks, so no task sees all lengths.

Defined cases: a null or empty text has length 0 (1 with an end id); rows that
repeat count each; a very long text is one more length; an empty table gives an
empty result. Extra columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import written
from .encoding import encoder

BLOCK = 1024


def length_histogram(docs: DataFrame, path: str, end: int = 0) -> DataFrame:
    """length, n_docs, written once: how many documents encode to each length, ``end`` ids included."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = Counter(len(ids) + end for ids in encoder(path).encode(batch.column(0).to_pylist()))
            yield pa.record_batch([pa.array(list(found), pa.int64()), pa.array(list(found.values()), pa.int64())], names=["length", "n"])

    return written(docs.select("text").mapInArrow(count, "length long, n long").groupBy("length").agg(F.sum("n").alias("n_docs")), "lengths")


def answers(histogram: DataFrame) -> DataFrame:
    """For every length, taken as a context limit too: documents and tokens at least as long,
    the total when all are cut to it, and the share of documents no longer than it (so the
    q-quantile is the first length whose share reaches q)."""
    counted = histogram.withColumn("tokens", F.col("n_docs") * F.col("length")).withColumn("block", F.floor(F.col("length") / BLOCK))
    longer = Window.orderBy(F.col("block").desc()).rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy()
    none = F.lit(0).cast("long")
    blocks = counted.groupBy("block").agg(F.sum("n_docs").alias("n"), F.sum("tokens").alias("t")).select(
        "block", *[F.coalesce(F.sum(c).over(longer), none).alias(f"{c}_longer") for c in "nt"], *[F.sum(c).over(everything).alias(f"{c}_all") for c in "nt"]
    )
    within = Window.partitionBy("block").orderBy(F.col("length").desc()).rowsBetween(Window.unboundedPreceding, 0)
    sums = counted.join(blocks, "block").withColumn("docs_at_least", F.sum("n_docs").over(within) + F.col("n_longer")).withColumn("tokens_at_least", F.sum("tokens").over(within) + F.col("t_longer"))
    cut = F.col("t_all") - F.col("tokens_at_least") + F.col("length") * F.col("docs_at_least")
    upto = (F.col("n_all") - F.col("docs_at_least") + F.col("n_docs")) / F.col("n_all")
    return sums.select("length", "n_docs", "tokens", "docs_at_least", "tokens_at_least", cut.alias("truncated_total"), upto.alias("share_upto"))
