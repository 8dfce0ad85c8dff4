"""The queries of the corpus operators, opN_<name>, and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import exact_dedup, lengths, mixing, packing, pseudonyms, quality, repeats, simhash, suffix_tree, wavelet
from .common import load


def op1_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_plan(load(spark, sf_dir, "documents"))


def tokenizer(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(load(spark, sf_dir, "documents"), tokenizer("word_bpe_49k.json"))


def op3_suffix_tree_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_tree.score(load(spark, sf_dir, "documents"))


def op4_wavelet_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wavelet.read_documents(wavelet.write_shards(load(spark, sf_dir, "documents"), tokenizer("byte_bpe_50k.json")))


def op5_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    groups = simhash.near_groups(load(spark, sf_dir, "documents"))
    return groups.select("doc_id", F.lower(F.lpad(F.hex("bits"), 16, "0")).alias("fingerprint"), "component_id")


def op6_pii_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pseudonyms.report(load(spark, sf_dir, "documents"))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judged(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lengths.answers(lengths.length_histogram(load(spark, sf_dir, "documents"), tokenizer("byte_bpe_50k.json")))


def op9_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = repeats.substring_dedup(load(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def op10_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(load(spark, sf_dir, "documents")).select("doc_id", "keep_id", "group_size", "kept", F.col("digest").alias("text_sha256"))


def queries() -> dict:
    return {f.__name__: f for f in (op1_source_mixing, op2_best_fit_packing, op3_suffix_tree_scores, op4_wavelet_shards, op5_simhash_near_dedup, op6_pii_pseudonyms, op7_quality_rules, op8_token_counts, op9_substring_dedup, op10_exact_dedup)}
