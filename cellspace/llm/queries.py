"""Queries of the training-data operators, each over its whole table with production parameters, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellspace.llm.bpe import bpe_encode
from cellspace.llm.exact_dedup import exact_groups
from cellspace.llm.language import fit_languages, language_labels
from cellspace.llm.licenses import license_scan
from cellspace.llm.lm import lm_log_likelihood
from cellspace.llm.packing import best_fit_pack
from cellspace.llm.quality import fit_quality, quality_scores
from cellspace.llm.secrets import secret_scan
from cellspace.llm.simhash import near_groups
from cellspace.llm.topk import exact_top_k


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _docs(spark, sf_dir)
    return quality_scores(docs, fit_quality(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _docs(spark, sf_dir)
    return language_labels(docs, fit_languages(docs))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_exact_dedup": lambda s, d: exact_groups(_docs(s, d)),
    "op2_license_scan": lambda s, d: license_scan(_docs(s, d)),
    "op3_secret_scan": lambda s, d: secret_scan(_docs(s, d)),
    "op4_exact_top_k": lambda s, d: exact_top_k(s.read.parquet(f"{d}/embeddings.parquet"), queries=F.col("vec_id") % 50 == 0),
    "op5_quality": op5_quality,
    "op6_simhash": lambda s, d: near_groups(_docs(s, d)),
    "op7_bpe": lambda s, d: bpe_encode(_docs(s, d)),
    "op8_lm_scores": lambda s, d: lm_log_likelihood(_docs(s, d)),
    "op9_language_id": op9_language_id,
    "op10_packing": lambda s, d: best_fit_pack(_docs(s, d)),
}

ORACLES: dict[str, str] = {
    "op1_exact_dedup": """
        SELECT doc_id,
               CASE WHEN text IS NULL THEN doc_id ELSE min(doc_id) OVER (PARTITION BY text) END AS keep_id,
               CASE WHEN text IS NULL THEN 1 ELSE count(*) OVER (PARTITION BY text) END AS copies,
               text IS NOT NULL AND row_number() OVER (PARTITION BY text ORDER BY doc_id) > 1 AS is_copy
        FROM documents""",
    "op4_exact_top_k": """
        WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings WHERE embedding IS NOT NULL),
        p AS (SELECT a.vec_id, b.vec_id AS neighbour, list_distance(a.x, b.x) AS d FROM v a JOIN v b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id),
        r AS (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY d, neighbour) AS k FROM p)
        SELECT vec_id, CAST(k AS INTEGER) AS rank, neighbour, round(d, 6) AS distance FROM r WHERE k <= 10""",
}
