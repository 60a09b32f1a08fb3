"""A corpus pipeline of the llm operators: each stage's rows are written and read again for the next.

Documents that the quality rules or the toxicity score reject go, one document of each near-duplicate class
stays, and what is left is packed into sequences.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from plate_engine.llm import near_dedup, packing, quality_rules, toxicity
from plate_engine.llm.common import documents, labels, stored


def reject_low_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_rules.keep_good(docs, labels(spark, sf_dir))


def reject_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.keep_clean(docs, labels(spark, sf_dir))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dedup.keep_one(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.packed(docs, public_tokenizers.path("byte_bpe_50k.json"), end_id=2)


STAGES = [("quality_rules", reject_low_quality), ("toxicity", reject_toxic), ("minhash_near_dedup", drop_near_duplicates), ("best_fit_packing", pack_sequences)]

#: Neighbour search, signatures and the tokenizer can't be said in SQL; tests compare with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
