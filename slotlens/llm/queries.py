"""Registry of the operators' queries, with production parameters over whole tables."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slotlens.llm import bpe, class_lm, near_copies, nearest, packing, quality, secrets, sharding, winnowing


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_class_ngram_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return class_lm.score(documents(spark, sf_dir))


def op2_heap_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = bpe.token_counts(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"))
    return counts.withColumn("over_limit", F.col("n_tokens") > 2048)


def op3_secret_ownership(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.report(documents(spark, sf_dir))


def op4_sum_of_squares_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = packing.pieces(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"), with_ids=False)
    return packing.pack(cut)


def op5_rule_ensemble_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet")
    return quality.score(docs, quality.fit(docs, labels))


def op6_minhash_forest_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_copies.join(documents(spark, sf_dir)).drop("row_id")


def op7_sampled_splitters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.by_bytes(documents(spark, sf_dir))


def op8_winnowing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return winnowing.neighbour_edits(documents(spark, sf_dir))


def op9_learned_partitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest.search(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


def op10_rank_array_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_digests(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"))


QUERIES = {
    "op1_class_ngram_lm": op1_class_ngram_lm,
    "op2_heap_token_counts": op2_heap_token_counts,
    "op3_secret_ownership": op3_secret_ownership,
    "op4_sum_of_squares_packing": op4_sum_of_squares_packing,
    "op5_rule_ensemble_quality": op5_rule_ensemble_quality,
    "op6_minhash_forest_join": op6_minhash_forest_join,
    "op7_sampled_splitters": op7_sampled_splitters,
    "op8_winnowing": op8_winnowing,
    "op9_learned_partitions": op9_learned_partitions,
    "op10_rank_array_bpe": op10_rank_array_bpe,
}

ORACLES: dict[str, str] = {"op3_secret_ownership": secrets.REPORT_SQL}
