"""The corpus pipeline: each stage works on all that its predecessor kept.

Stages are written one after another; a stage's intermediate tables and its input go once its output is complete.

Defined results, as the operators state them: a null text fails the quality rules, as do texts of white space; rows
of equal id are versions of one document, which line dedup decides alike and near-dedup keeps or drops together; rows
with a null id are judged like others and stay in near-dedup; an empty table gives an empty one in every stage; extra
columns, whatever their names, pass all stages but the last.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from vertexlog.llm import decontaminate, line_dedup, packing, quality, simhash
from vertexlog.llm.common import Scratch, read_table, temporary


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep_good(docs)


def line_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return line_dedup.without_repeats(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.keep_one_of_each(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.remove_contaminated(docs, read_table(spark, sf_dir, "benchmark"))


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality rules", quality_rules),
    ("line dedup", line_repeats),
    ("simhash near-dedup", near_dedup),
    ("benchmark decontamination", decontamination),
    ("best-fit packing", best_fit_packing),
]

#: The stages hash shingles, cut by rolling hashes and tokenize: SQL can't express that; see the brute-force test.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    scratch = Scratch(spark, "pipeline")
    for _, stage in STAGES:
        with temporary(spark):
            docs = scratch.keep(stage(spark, docs, sf_dir))
        scratch.forget(1)
    return docs
