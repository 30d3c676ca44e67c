"""A training corpus from the documents table: language, near copies, repeated passages, mixture, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from shapeplan.llm import stages
from shapeplan.runtime import table, written

STAGES = [
    ("language_id", stages.keep_identified),
    ("minhash_near_dedup", stages.keep_one_of_near_copies),
    ("substring_dedup", stages.drop_repeated_passages),
    ("mixing", stages.mix_sources),
    ("packing", stages.pack_sequences),
]

#: Tokenizers and language models are beyond SQL; tests compare the stages with brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
