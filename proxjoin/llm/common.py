"""Helpers that the corpus operators share: inputs, written intermediates, word rules."""

from __future__ import annotations

import tempfile
import uuid
import weakref

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .blobs import slots_counted

#: Fixed values of the word rule: ASCII white space separates words.
SPACES = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"
#: Slots of dropped rows that a plan carries, as a power of two: 32 KB.
MARKS = 18

#: Deletes the shuffle files of a plan when it has ended.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"

_own_folder: dict[str, str] = {}
_written: weakref.WeakKeyDictionary[DataFrame, str] = weakref.WeakKeyDictionary()


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir.

    Only a local session, where driver and executors are one process, gets a
    folder of its own when the setting is missing.
    """
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    app = spark.sparkContext.applicationId
    if app not in _own_folder:
        _own_folder[app] = "file://" + tempfile.mkdtemp(prefix="proxjoin-")
    return _own_folder[app]


def written(df: DataFrame, label: str, codec: str = "zstd") -> DataFrame:
    """df as a table in the shared folder: lineage ends here, lost executors cost
    only the rows after it, and its size is known to the planner. The table goes
    when the application ends; the shuffle files of the write go at once, as no
    other plan reads them."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/proxjoin/{label}-{uuid.uuid4().hex}"
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.option("compression", codec).parquet(path)
    finally:
        spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)
    files, target = _folder(spark, path)
    files.deleteOnExit(target)
    out = spark.read.schema(df.schema).parquet(path)
    _written[out] = path
    return out


def _folder(spark: SparkSession, path: str):
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), target


def discarded(*tables: DataFrame) -> None:
    """Deletes written tables that no later plan reads."""
    for table in tables:
        path = _written.pop(table, None)
        if path:
            files, target = _folder(table.sparkSession, path)
            files.delete(target, True)


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Column names that clash with none of df's, whatever extra columns it has."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in names:
        while name.lower() in taken:
            name = f"_{name}"
        taken.add(name.lower())
        out.append(name)
    return out


def let(value: Column, body) -> Column:
    """body(value) with value worked out once, though body uses it many times."""
    return F.transform(F.array(value), body)[0]


def words(text: Column) -> Column:
    """The words of a text; none for a null."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SPACES, -1), "")


def unit_draw(*tags: Column | str) -> Column:
    """A number in [0, 1) that depends on the tags alone: 52 bits of their MD5."""
    text = F.concat_ws(":", *[F.coalesce(F.col(t).cast("string") if isinstance(t, str) else t.cast("string"), F.lit("null")) for t in tags])
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long") / F.lit(float(16**13))


def text_key(text: Column) -> Column:
    """Tells texts apart; a null text is the empty text."""
    return F.unhex(F.sha2(F.coalesce(text, F.lit("")), 256))


def one_of_each(docs: DataFrame, groups: DataFrame) -> DataFrame:
    """The docs with one row of each label of groups (doc_id, key, label: a row for each of docs); same columns.

    Rows are told apart by doc_id and text_key: the smallest doc_id stays, a null
    after all others, then the smallest key. Of rows that share both, the smallest
    by its columns stays, which must be of types that can be ordered.
    """
    key, gone, text = fresh(docs, "key", "gone", "twin")
    place = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "key")
    several = groups.groupBy("label").agg(F.min(place).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1")
    rows = written(groups.join(several, "label").select("doc_id", "key", place.eqNullSafe(F.col("first")).alias("stays")), "several")
    keyed = docs.withColumn(key, text_key(F.col("text")))
    named = lambda some: some.select(F.col("doc_id").alias(gone), F.col("key").alias(text))
    dropped = named(rows.where("not stays")).distinct()
    twins = named(rows.where("stays").groupBy("doc_id", "key").count().where("count > 1"))
    whole = not twins.isEmpty()
    dropped = dropped.union(twins) if whole else dropped
    # most rows share no slot with a dropped one and stay where they are; the others are joined
    slot = lambda doc_id, text: F.pmod(F.xxhash64(F.col(doc_id).cast("long"), text), F.lit(1 << MARKS))
    marked = slots_counted(dropped.select(slot(gone, text).alias("slot")), lambda batch: iter([batch.column(0).to_numpy()]))[: 1 << MARKS] > 0
    bits, place = F.lit(bytearray(np.packbits(marked, bitorder="little").tobytes())), slot("doc_id", key)
    byte = F.conv(F.hex(F.substring(bits, (F.floor(place / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("long")
    maybe = F.call_function("getbit", byte, (place % 8).cast("int")) == 1
    some = keyed.where(maybe)
    same = lambda other: some["doc_id"].eqNullSafe(other[gone]) & (some[key] == other[text])
    kept = keyed.where(~maybe).union(some.join(dropped, same(dropped), "left_anti")).drop(key)
    if not whole:
        return kept
    fields = F.struct(*[F.col(c).alias(f"c{k}") for k, c in enumerate(docs.columns)])
    least = some.join(twins, same(twins), "left_semi").groupBy("doc_id", key).agg(F.min(fields).alias(gone))
    return kept.union(least.select(*[F.col(f"{gone}.c{k}").alias(c) for k, c in enumerate(docs.columns)]))
