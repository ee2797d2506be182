"""The registered queries of these operators, with production parameters, over whole tables."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import binary_output, line_dedup, oracles, packing, prefix_bpe, quality, sharding, simhash, suffix_dedup, topk, toxicity
from .common import documents

RANKS = public_tokenizers.path("byte_bpe_50k.tiktoken")
PATTERN = public_tokenizers.PATTERN


def op1_cost_balanced_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir), RANKS, PATTERN, room=1024, end_id=0)


def op2_run_length_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = suffix_dedup.dedup(documents(spark, sf_dir, "doc_id", "text"), length=100)
    return df.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")


def op3_line_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = line_dedup.dedup_lines(documents(spark, sf_dir, "doc_id", "text"))
    return df.select("doc_id", "n_lines", "n_removed", "longest_run", "kept_text")


def op4_subsequence_kernel_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return toxicity.judge(documents(spark, sf_dir), labels, limit=0.3)


def op5_maxscore_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return topk.top_k(vectors, vectors.filter("vec_id % 50 = 0"), k=5, scale=256)


def op6_distribution_divergence(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = quality.judge(documents(spark, sf_dir))
    return df.withColumns({c: F.round(c, 6) for c in ("class_distance", "word_distance", "class_limit", "word_limit")})


def op7_kd_tree_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(documents(spark, sf_dir))


def op8_prefix_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prefix_bpe.encode(documents(spark, sf_dir), RANKS, PATTERN)


def op9_simhash_trie(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(documents(spark, sf_dir), words=4, budget=4, seed=42)


def op10_binary_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return binary_output.matrices(documents(spark, sf_dir), RANKS, PATTERN)


QUERIES = {f.__name__: f for f in (op1_cost_balanced_packing, op2_run_length_index, op3_line_suffix_array, op4_subsequence_kernel_toxicity, op5_maxscore_top_k, op6_distribution_divergence, op7_kd_tree_sharding, op8_prefix_bpe, op9_simhash_trie, op10_binary_output)}
ORACLES: dict[str, str] = {
    "op2_run_length_index": oracles.RUN_LENGTH_INDEX,
    "op3_line_suffix_array": oracles.line_suffix_array(),
    "op5_maxscore_top_k": oracles.MAXSCORE,
    "op6_distribution_divergence": oracles.distribution_divergence(),
}
