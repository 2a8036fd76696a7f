"""A corpus pipeline of five stages over ``documents``; each works on all that its predecessor kept.

Ids may be null, repeated and of any type that can be ordered; further columns are carried through all stages but the
last. An empty table gives no row.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from cellspace.llm.common import staged
from cellspace.llm.exact_dedup import drop_copies
from cellspace.llm.packing import best_fit_pack
from cellspace.llm.quality import fit_quality, keep_quality
from cellspace.llm.secrets import mask_secrets
from cellspace.llm.simhash import drop_near_copies


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier, fitted to a bounded sample of labelled ones, doesn't reject.

    Null, empty and blank texts go; null ids and repeated rows are judged by their text. Without labels of both classes
    every document with text stays.
    """
    return keep_quality(docs, fit_quality(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def without_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each text: that of the least id, nulls last. Null texts all stay, empty ones are one text."""
    return drop_copies(docs)


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: that of the least id, nulls last. Texts without words all stay."""
    return drop_near_copies(docs)


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The same documents with secrets masked; no row goes, null and empty texts stay as they are."""
    return mask_secrets(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each document lies in which sequence, in tokens; a text without tokens has one row without
    a place, a repeated row is packed again."""
    return best_fit_pack(docs)


STAGES = [
    ("quality classifier", good_quality),
    ("exact dedup", without_copies),
    ("SimHash near-dedup", without_near_copies),
    ("secret scans", without_secrets),
    ("best-fit packing", packed),
]

#: SQL cannot express the fitted classifier; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = staged(docs, f"stage{k}")
    return docs
