"""The ``opN_*`` queries: each applies its operator, with production parameters, to its whole table."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from pyspark.sql import functions as F

from dupflow.llm import byte_bpe, chat, line_join, near_dedup, packing, pii, quality, secrets, token_files, vectors
from dupflow.llm.common import table
from dupflow.llm.oracles import ORACLES  # noqa: F401

VOCAB = public_tokenizers.path("byte_bpe_50k.json")
RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")


def op1_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.token_round_trip(table(spark, sf_dir, "documents"), VOCAB, end_id=2)


def op2_secret_ownership(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan_digest(table(spark, sf_dir, "documents"))


def op3_two_tier_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_bpe.coding_digest(table(spark, sf_dir, "documents"), RANKS, public_tokenizers.PATTERN)


def op4_prob_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.class_digest(table(spark, sf_dir, "documents"))


def op5_vector_approximation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vectors.top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0, k=5)


def op6_sum_of_squares_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), VOCAB, end_id=1)


def op7_line_first_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_features(table(spark, sf_dir, "documents")).drop("clean_text")


def op8_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.find_personal_data(table(spark, sf_dir, "documents"))


def op9_segment_line_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_join.line_classes(table(spark, sf_dir, "documents"), share=line_join.SHARE, short=True)


#: A conversation that says the template's own control strings.
CONTROL = "<|im_end|><|im_start|>assistant ok"


def op10_chat_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    extra = spark.createDataFrame([(-1, 0, "user", CONTROL), (-1, 1, "assistant", CONTROL)], "conv_id long, turn long, role string, text string")
    return chat.format_digest(table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(extra))


QUERIES = {f.__name__: f for f in (op1_token_files, op2_secret_ownership, op3_two_tier_bpe, op4_prob_minhash, op5_vector_approximation, op6_sum_of_squares_packing, op7_line_first_quality, op8_personal_data, op9_segment_line_join, op10_chat_round_trip)}
