"""A corpus pipeline of five operators; every stage's result is written and read again by the next one.

A stage begins when the result of the one before has been written, and then clears its working tables.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from orthant.llm import classifiers, jaccard, mixing, packing, quality_rules
from orthant.llm.shared import materialize, scope, table


def quality_rules_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base rule or are outliers of their language and source go."""
    with scope(spark, "pipeline"):
        return quality_rules.kept_documents(docs)


def quality_classifier_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier doesn't find good go. It learns from the labelled rows of the whole table
    ``documents``, as the rules before it took most bad examples away."""
    with scope(spark, "pipeline"):
        return classifiers.good_documents(docs, table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def jaccard_join_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays."""
    with scope(spark, "pipeline"):
        return jaccard.representatives(docs)


def mix_sources_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document comes as often as the mix takes it."""
    with scope(spark, "pipeline"):
        return mixing.mixed_documents(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of packed sequences, with their ids."""
    with scope(spark, "pipeline"):
        return packing.packed_public(docs)


STAGES = [
    ("quality rules", quality_rules_stage),
    ("quality classifier", quality_classifier_stage),
    ("n-gram Jaccard join", jaccard_join_stage),
    ("mixing sources", mix_sources_stage),
    ("packing", packing_stage),
]

#: SQL can't express the fits, the automata of the tokenizer and the classifier; tests hold stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = materialize(docs, "pipeline-stage")
    return docs
