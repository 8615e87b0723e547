"""A corpus from raw documents: five stages, each an operator of basepack.llm, each written before the next reads it.

Decisions: documents under the quality threshold go; one document of each SimHash class stays; strings of 200
bytes that occur elsewhere are cut, and a document cut to nothing goes; contaminated documents go; the mix
keeps the documents of which it takes words, with how often and how many.

Defined results: null and empty texts are judged like any other and are one SimHash class; null and repeated ids are rows of
their own; an empty table gives an empty result; extra columns go along whatever their names, and the mix adds its own (mix_...).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from basepack.llm import decontaminate, mixing, quality, simhash, substrings
from basepack.llm.common import materialise, table


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep_good(docs, table(spark, sf_dir, "labels"))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.keep_one(docs)


def substring_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return substrings.without_repeats(docs)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.keep_clean(docs, table(spark, sf_dir, "benchmark"))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mix(docs).where("mix_copies > 0")


STAGES = [
    ("quality", quality_stage),
    ("near_duplicates", near_duplicate_stage),
    ("substrings", substring_stage),
    ("decontamination", decontamination_stage),
    ("mixing", mixing_stage),
]

#: The stages with a fitted model, fingerprints and suffixes have no SQL form; tests/llm compares with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
