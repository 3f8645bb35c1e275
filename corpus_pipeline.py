"""A corpus pipeline of five stages over documents; see ``sampledjoin.llm`` for the operators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from sampledjoin.llm import common, decontam, linededup, neardup, spm, toxicity

STAGES = [
    ("toxicity", toxicity.toxicity_stage),
    ("line_dedup", linededup.line_stage),
    ("near_dedup", neardup.near_stage),
    ("decontamination", decontam.decontamination_stage),
    ("sentencepiece", spm.encoding_stage),
]

#: Learned scores, sampled similarity and a tokenizer: not for SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each stage's result is a table that the next one reads."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = common.materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
