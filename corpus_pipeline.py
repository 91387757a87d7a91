"""The corpus pipeline: five stages over `documents`, each written as Parquet and read again.

Every stage takes (spark, docs, sf_dir), works on all rows its predecessor kept and returns the
columns of documents. Nulls, empty tables and clashing extra columns are treated as each
operator's module says. Counted as part of the training-data subpackage.

1. language: documents without a letter, or whose language is told with a score below 0.3, go;
2. one_of_each: one document of each group of near copies stays, that of the smallest id;
3. leaks: documents that hold part of a benchmark item go;
4. private_data: identifiers are replaced by their kind in square brackets;
5. mix: documents repeat as their source's rate says.
"""

from __future__ import annotations

from collections.abc import Callable

from attrition.llm import language, leaks, mixing, private_data, similar_sets
from attrition.llm.common import documents, saved
from pyspark.sql import DataFrame, SparkSession

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _own(docs: DataFrame) -> DataFrame:
    return docs.select(*COLUMNS)


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language.accepted(_own(docs), least=0.3)


def similar_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return similar_sets.one_of_each(_own(docs))


def leak_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return leaks.without_leaks(_own(docs), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def private_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return private_data.redacted(_own(docs))


def mix_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.emitted(_own(docs))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("language", language_stage),
    ("one_of_each", similar_stage),
    ("leaks", leak_stage),
    ("private_data", private_stage),
    ("mix", mix_stage),
]

#: The language network, the attested groups and the discovered identifiers are beyond SQL; tests hold run() against
#: a brute-force version instead.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES:
        docs = saved(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
