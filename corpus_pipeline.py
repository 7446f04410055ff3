"""A corpus pipeline of the training-data operators: each stage works on what the one before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from farpoint.llm.common import Staging, read_table
from farpoint.llm.decontam import drop_contaminated
from farpoint.llm.langid import keep_identified, train
from farpoint.llm.line_dedup import line_dedup
from farpoint.llm.simhash import drop_near_duplicates
from farpoint.llm.sp_sample import sampled_encodings


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no language is found go."""
    return keep_identified(docs, train(docs))


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of line runs are cut out of the texts."""
    return line_dedup(spark, docs).select(docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates stays."""
    return drop_near_duplicates(spark, docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold benchmark passages go."""
    return drop_contaminated(spark, docs, read_table(spark, sf_dir, "benchmark"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sampled segmentations of the texts that are left."""
    return sampled_encodings(docs)


STAGES = [("language_id", language_id), ("line_dedup", dedup_lines), ("near_dedup", near_dedup), ("decontaminate", decontaminate), ("sentencepiece", encode)]

#: Neither the network's decisions nor the sampled encodings can be told in SQL; tests/llm holds the rows against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    stage, docs = Staging(spark, "pipeline"), read_table(spark, sf_dir, "documents")
    for name, step in STAGES[:-1]:
        docs = stage.keep(step(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
