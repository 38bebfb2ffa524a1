"""A training corpus from ``documents``: five stages, each an operator of the ``llm`` subpackage applied to all that the one before kept.

Defined results. Null and empty texts, and texts without letters, go in the first stage (they have no language). Null ids: kept where their text is, linked with
nothing and cut by nothing. Repeated rows: kept or rejected alike by the filters; near duplicates compare ids, so rows that repeat an id stay together. Ties: the
least id stays. Texts are read whole, however long. Extra columns are carried to the last stage, whatever their names. Empty tables: no rows from any stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ergodica.llm import decontaminate, langid, neardup, packing, substrings
from ergodica.llm.common import table, written

LEAST_SCORE = 0.3  # four languages: a text whose best language has less is no language


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects texts without letters and texts of no learnt language."""
    return langid.filter_languages(docs, langid.train(docs), least=LEAST_SCORE)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents whose sets of five-word shingles have a similarity of 0.8 or more, the least id stays."""
    return neardup.keep_one(docs)


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts 13-word windows that a document with a smaller id has too."""
    return substrings.without_repeats(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents that hold a benchmark passage."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces with their place in the packed sequences, and their ids."""
    return packing.pack(docs, packing.tokenizer_path(), with_ids=True)


STAGES = [
    ("language_id", language_id),
    ("near_dedup", near_dedup),
    ("substring_dedup", substring_dedup),
    ("decontamination", decontamination),
    ("best_fit_packing", packing_stage),
]

ORACLE_SQL = None  # a trained network and a tokenizer have no SQL; tests/llm/test_pipeline.py holds stages 2 to 4 against brute force, packed ids against the tokenizer's


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), name)
    return docs
