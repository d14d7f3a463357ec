"""A training corpus from raw documents: five stages, each written as Parquet and read again.

Every stage is one operator of the training-data subpackage: documents that are toxic
go, then those of no recognisable language, then lines that repeat earlier ones, then
all but one of each group of near duplicates; the rest is packed into windows.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from tidelabel.llm import language, line_dedup, minhash, packing, toxicity
from tidelabel.llm.common import documents, materialise

#: A document is kept if its language holds at least this share of its character n-grams.
LEAST_KNOWN = 0.4


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the class-conditional models don't predict to be toxic."""
    return toxicity.without_toxic(docs, toxicity.train(docs, toxicity.training_labels(spark, sf_dir)))


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with letters whose n-grams fit a language; filters are learned as for the query."""
    filters = language.learn(docs.where(~language.held_out()).select("lang", "text"))
    return language.with_language(docs, filters, LEAST_KNOWN)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return line_dedup.without_duplicate_lines(docs, line_dedup.duplicate_lines(docs))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group: that of the smallest doc_id; rows are told by id and text."""
    return minhash.one_of_each(docs, minhash.near_groups(docs))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", toxicity_stage),
    ("language", language_stage),
    ("line_dedup", line_stage),
    ("near_dedup", near_duplicate_stage),
    ("packing", packing_stage),
]

#: SQL has no language models and no tokeniser: the stages are tested against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return materialise(STAGES[-1][1](spark, docs, sf_dir), f"pipeline-{STAGES[-1][0]}")
