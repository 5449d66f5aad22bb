"""A corpus pipeline: quality rules, line dedup, near duplicates, source mix, packing.

Each stage works on all that its predecessor kept; all but the last return the columns of ``documents``, whatever
further columns there are. Every stage gives no rows for no rows, reads whole texts however long, and treats repeated
rows and ties alike at every run.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from componentry.llm import jaccard, lines, mixing, packing, quality
from componentry.plans.storage import cut


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and the adaptive thresholds of their language and source.

    Null and empty texts have no words and go. Null language or source: a group of its own. Repeated rows are judged alike.
    """
    return quality.keep_good(docs)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without their source's boilerplate lines; no row goes.

    Null texts stay null, a text all of boilerplate becomes empty; rows without a source form one site.
    """
    return lines.drop_boilerplate(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates, that with the smallest doc_id.

    Of rows that repeat id and text one stays; texts without a word and rows without an id stay as they are.
    """
    return jaccard.keep_one(docs)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them, in its order within each part.

    Texts without a word are never taken; rows without a source are a source; repeated rows are documents of their own.
    """
    return mixing.mixed_documents(docs)


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of token pieces; a null or empty text is the end id alone, repeated rows are packed each."""
    return packing.pack_documents(docs)


STAGES = [(f.__name__, f) for f in (quality_rules, line_dedup, near_duplicates, source_mix, best_fit_packing)]

#: the tokeniser and the near-duplicate classes have no SQL: tests/llm holds the stages against brute force
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = cut(docs, name)
    return docs
