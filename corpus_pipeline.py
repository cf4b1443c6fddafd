"""Corpus pipeline: five of the training-data operators in a row, each on all that its predecessor kept.

Every stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame, which is written as Parquet and read again as the
next one's ``docs``. All but the last return the columns of ``documents``; the last adds the domain, the tokens and the
number of epochs that take the document.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from varlink.llm import decontamination, line_dedup, mixing, near_copies, quality
from varlink.llm.common import load, new_path


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base rules or an adaptive fence go."""
    return quality.quality_filter(docs)


def line_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines repeated over documents go, but for one place each; all documents stay."""
    return line_dedup.drop_repeated_lines(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: fingerprints within two bits link, found by the segment variants of
    operator 7, and so do five-word shingles with a similarity of 0.8 or more."""
    return near_copies.drop_similar(docs, prints=True)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go."""
    return decontamination.decontaminate(docs, load(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each leaf's seeded token prefix, with ``domain``, ``n_tokens`` and ``copies``."""
    mixed, (domain, n_tokens, copies) = mixing.mix(docs)
    return mixed.withColumnsRenamed({domain: "domain", n_tokens: "n_tokens", copies: "copies"}) if not {"domain", "n_tokens", "copies"} & set(docs.columns) else mixed


STAGES = [("quality_rules", quality_rules), ("line_dedup", line_dedup_stage), ("near_dedup", near_dedup), ("decontamination", decontaminate), ("source_mix", mix_sources)]

#: Similarity links and their components are beyond SQL: the run is tested against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written and read again."""
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = new_path(spark, f"pipeline-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
