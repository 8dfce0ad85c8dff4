"""Points frames (id, feat) from the given tables, checks of them, and sinks of pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import features as f

#: The feature type that each metric wants.
KINDS = {"hamming": ("bigint",), "l1": ("array<int>", "array<double>", "array<float>"), "l2": ("array<float>", "array<double>", "array<int>"), "jaccard": ("array<bigint>",), "cosine": ("array<float>", "array<double>")}


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def require_points(points: DataFrame, metric: str, unique: bool = False) -> DataFrame:
    """The points with a feature; a wrong schema, and on request a repeated id, is an error."""
    kinds = dict(points.dtypes)
    if kinds.get("id") != "bigint" or kinds.get("feat") not in KINDS[metric]:
        raise TypeError(f"{metric} wants (id bigint, feat {' or '.join(KINDS[metric])}), not {points.dtypes}")
    if unique and not points.groupBy("id").count().where("count > 1").isEmpty():
        raise ValueError("ids repeat")
    return points.select("id", "feat").where(F.col("id").isNotNull() & F.col("feat").isNotNull())


def spread(df: DataFrame) -> DataFrame:
    """Small tables come as one row group; quadratic steps want all cores."""
    return df.repartition(max(8, df.sparkSession.sparkContext.defaultParallelism)) if df.rdd.getNumPartitions() < 4 else df


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")


def load_points(spark: SparkSession, sf_dir: str, fixture: str) -> DataFrame:
    """The points of a fixture, by its name in FIXTURES.md."""
    table = lambda name: load_table(spark, sf_dir, name)
    docs = lambda: spread(documents(spark, sf_dir))
    build = {
        "doc_words": lambda: docs().select("id", f.word_set(F.col("text")).alias("feat")),
        "doc_shingles": lambda: docs().select("id", f.shingle_set(F.col("text")).alias("feat")).where(F.size("feat") > 0),
        "doc_signed256": lambda: f.signed_vectors(docs().select("id", f.word_set(F.col("text")).alias("feat"))),
        "doc_counts64": lambda: f.count_vectors(docs()),
        "doc_finger64": lambda: f.fingerprints64(docs()),
        "emb": lambda: spread(table("embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("feat"))),
        "emb_sign": lambda: table("embeddings").select(F.col("vec_id").alias("id"), f.sign_bits(F.col("embedding")).alias("feat")),
        "page_words": lambda: spread(table("pages").select(F.col("page_id").alias("id"), "html")).select("id", f.word_set(F.col("html")).alias("feat")),
        "conv_words": lambda: spread(table("conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text")).select("id", f.word_set(F.col("text")).alias("feat")),
        "bench_words": lambda: table("benchmark").select(F.col("item_id").alias("id"), f.word_set(F.col("text")).alias("feat")),
        "doc_lines": lambda: docs().select("id", F.posexplode(F.split("text", "\n", -1)).alias("line", "text")).select((F.col("id") * 100_000 + F.col("line")).alias("id"), f.word_set(F.col("text")).alias("feat")).where(F.size("feat") > 0),
        "cust_brands": lambda: f.group_sets(
            # a brand is hashed once for each part, not for each line
            table("orders").select("o_orderkey", "o_custkey").join(table("lineitem").select("l_orderkey", "l_partkey"), F.col("o_orderkey") == F.col("l_orderkey"))
            .join(table("part").select("p_partkey", f.md5_number(F.col("p_brand")).alias("brand")), F.col("l_partkey") == F.col("p_partkey")),
            "o_custkey", "brand",
        ),
        "user_hist": lambda: f.user_histogram(table("events"), f.EVENT_TYPES),
    }
    return build[fixture]()


def write_pairs(pairs: DataFrame, path: str, by_level: bool = False) -> None:
    """The listed result: parquet, by the level that found a pair where it has one."""
    writer = pairs.write.mode("overwrite")
    (writer.partitionBy("level") if by_level and "level" in pairs.columns else writer).parquet(path)


def save_hash_index(rows: DataFrame, name: str, buckets: int = 16) -> None:
    """Rows (tag, key, id) as a table bucketed by key: later joins with it shuffle only the other side."""
    rows.write.mode("overwrite").bucketBy(buckets, "tag", "key").sortBy("tag", "key").saveAsTable(name)
