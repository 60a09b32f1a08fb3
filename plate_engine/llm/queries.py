"""The registered query of each operator, with its production parameters, and SQL where it can say the same."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from . import katz, near_dedup, packing, piece_codec, quality_model, quality_rules, token_blocks, token_counts, toxicity, version_sketch
from .common import documents, fold, labels
from .quality_sql import OP1_SQL


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.verdicts(documents(spark, sf_dir), labels(spark, sf_dir))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    found = toxicity.toxicity(docs, labels(spark, sf_dir), train=fold(3) != 1)
    return found.withColumn("held_out", fold(3) == 1)


def op3_katz(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = katz.katz_scores(documents(spark, sf_dir), train=fold(7) != 2)
    return found.withColumn("held_out", fold(7) == 2)


def op4_quality_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = quality_model.quality(documents(spark, sf_dir), labels(spark, sf_dir), train=fold(5) != 0)
    return found.withColumn("held_out", fold(5) == 0)


def op5_bagminhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_classes(documents(spark, sf_dir))


def op6_token_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_blocks.token_blocks(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"), end_id=1)


def op7_version_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return version_sketch.versions(documents(spark, sf_dir))


def op8_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"), end_id=2)


def op9_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_codec.piece_digests(documents(spark, sf_dir), public_tokenizers.path("piece_bpe_32k.model"))


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"), limit=512)


QUERIES = {f.__name__: f for f in (op1_quality_rules, op2_toxicity, op3_katz, op4_quality_model, op5_bagminhash, op6_token_blocks, op7_version_sketch, op8_best_fit_packing, op9_sentencepiece, op10_token_counts)}
ORACLE_SQL: dict[str, str] = {"op1_quality_rules": OP1_SQL}
