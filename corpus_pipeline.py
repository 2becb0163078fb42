"""From raw documents to packed sequences: language, near duplicates, secrets, mixture, packing.

Each stage works on all that the one before kept. Documents without any letter go, and those whose words no mixture of
the learned languages explains; a null lang is filled with the language found. One document of each group of near
duplicates stays, that of the smallest id; secrets are replaced by their kind in angle brackets and the documents stay;
documents are repeated to their source's target (some of an over-full source go); packing returns the pieces.
Null texts have no letter and go in the first stage. An empty table gives an empty result at every stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from setvec.llm import language, mixing, near, packing, secrets
from setvec.llm.common import documents, stored


def tell_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language.accepted(docs, language.trained(docs))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near.kept(docs)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return secrets.redacted(docs, stored(secrets.scan(docs), "secrets"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.repeated(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.packed(docs)


STAGES = [
    ("language", tell_languages),
    ("near_duplicates", drop_near_duplicates),
    ("secrets", redact_secrets),
    ("mixing", mix_sources),
    ("packing", pack),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what a stage returns is written and read again before the next."""
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
