"""Exact dedup by skew-safe combining, with DataFrame functions only.

Documents are combined within their partition first, then by (digest, salt,
content), then salt winners by (digest, content): a text that a third of all
rows share reaches a reducer as at most one row per salt and partition. Content stands beside
its digest in every grouping key, so equal digests of different texts never
merge. The mapping back to rows uses digests alone where each belongs to one
content, and else the content as well.

Defined cases: a null text is the empty text; a null doc_id sorts after all
others, and where no row of a group has an id, all of its rows are kept; rows
that repeat a doc_id have a result row each, and all of them count in
group_size; those that also repeat the text of the kept row are all marked kept,
as nothing tells them apart; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACES, fresh, written

SALTS = 16


def sha256(content: Column) -> Column:
    return F.sha2(content, 256)


def content_of(text: Column) -> Column:
    """The text with each run of white space as one space; texts are equal when these are."""
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACES, " ")


def salt_of(doc_id: Column, salts: int = SALTS) -> Column:
    """The salt of a row: rows without an id have the first."""
    return F.when(doc_id.isNull(), F.lit(0)).otherwise(F.pmod(F.xxhash64(doc_id), F.lit(salts)).cast("int"))


def combined(docs: DataFrame, digest: Callable[[Column], Column] = sha256, salts: int = SALTS) -> DataFrame:
    """digest, content, keep_id, group_size and salts (bit k for salt k): a row for each distinct content.

    The map side of the first grouping is the local dedup: for each content one
    row for each salt leaves a partition.
    """
    rows = docs.select(F.col("doc_id").alias("id"), content_of(F.col("text")).alias("content"))
    keyed = rows.select("id", "content", digest(F.col("content")).alias("digest"), salt_of(F.col("id"), salts).alias("salt"))
    winners = keyed.groupBy("digest", "salt", "content").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("n"))
    salt = F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("salt"))).alias("salts")
    return winners.groupBy("digest", "content").agg(F.min("id").alias("keep_id"), F.sum("n").alias("group_size"), salt)


def exact_groups(docs: DataFrame, digest: Callable[[Column], Column] = sha256, salts: int = SALTS) -> DataFrame:
    """doc_id, digest, keep_id, group_size, kept: one row for each row of docs.

    A row meets its group under the digest and its salt, and a group stands under
    the salts that it has, so the rows of a hot text meet in as many tasks.
    """
    groups = written(combined(docs, digest, salts).drop("content"), "groups")
    content = content_of(F.col("text"))
    rows = docs.select("doc_id", digest(content).alias("digest"), content.alias("content"), salt_of(F.col("doc_id"), salts).alias("salt"))
    on = ["digest", "salt"]
    if groups.groupBy("digest").count().where("count > 1").isEmpty():
        rows = rows.drop("content")
    else:
        groups, on = combined(docs, digest, salts), [*on, "content"]
    has = F.filter(F.sequence(F.lit(0), F.lit(salts - 1)), lambda k: F.call_function("getbit", F.col("salts"), k) == 1)
    members = rows.join(groups.withColumn("salt", F.explode(has)).drop("salts"), on)
    return members.select("doc_id", "digest", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"))


def exact_dedup(docs: DataFrame, digest: Callable[[Column], Column] = sha256, salts: int = SALTS) -> DataFrame:
    """docs with one row of each content, the one with the smallest doc_id; same columns.

    The same two groupings carry the best whole row instead of its id, so nothing
    is joined back. Of rows that repeat a doc_id, the smallest by the other
    columns stays, which must be of types that can be ordered. A text travels
    beside its content only where the two differ.
    """
    content, digest_, salt, row = fresh(docs, "content", "digest", "salt", "row")
    rest = [c for c in docs.columns if c not in ("doc_id", "text")]
    shape = content_of(F.col("text"))
    raw = F.when(F.col("text").isNull() | (F.col("text") != shape), F.struct(F.col("text").alias("text")))
    fields = [F.col("doc_id").isNull().alias("no_id"), F.col("doc_id").alias("id"), *[F.col(c).alias(f"c{k}") for k, c in enumerate(rest)], raw.alias("raw")]
    rows = docs.select(shape.alias(content), F.struct(*fields).alias(row))
    keyed = rows.select(content, row, digest(F.col(content)).alias(digest_), salt_of(F.col(f"{row}.id"), salts).alias(salt))
    winners = keyed.groupBy(digest_, salt, content).agg(F.min(row).alias(row))
    kept = winners.groupBy(digest_, content).agg(F.min(row).alias(row))
    text = F.when(F.col(f"{row}.raw").isNull(), F.col(content)).otherwise(F.col(f"{row}.raw.text"))
    values = {"doc_id": F.col(f"{row}.id"), "text": text} | {c: F.col(f"{row}.c{k}") for k, c in enumerate(rest)}
    return kept.select(*[values[c].alias(c) for c in docs.columns])
