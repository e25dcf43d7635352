"""The registered queries of this subpackage and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ebbset.llm import bpe, chaining, fingerprint, jaccard, langid, mtree, packing, pii, suffix, tokenfile
from ebbset.llm._spark import documents


def op1_chained_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chaining.passages(documents(spark, sf_dir))


def op2_partial_matching(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.digest(documents(spark, sf_dir))


def op3_bottom_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.neighbours(documents(spark, sf_dir))


def op4_suffix_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix.digest(documents(spark, sf_dir))


def op5_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.jaccard_components(documents(spark, sf_dir), jaccard.Measure(width=4, low=85, high=100))


def op6_bpe_folds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digest(documents(spark, sf_dir))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir))


def op8_mtree_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mtree.top_k(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), every=50, k=5, scale=256)


def op9_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenfile.round_trip(documents(spark, sf_dir))


def op10_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digest(documents(spark, sf_dir))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_chained_passages": op1_chained_passages,
    "op2_partial_matching": op2_partial_matching,
    "op3_bottom_k": op3_bottom_k,
    "op4_suffix_windows": op4_suffix_windows,
    "op5_jaccard_join": op5_jaccard_join,
    "op6_bpe_folds": op6_bpe_folds,
    "op7_packing": op7_packing,
    "op8_mtree_top_k": op8_mtree_top_k,
    "op9_token_files": op9_token_files,
    "op10_pii": op10_pii,
}

ORACLE: dict[str, str] = {
    "op8_mtree_top_k": """
        WITH valid AS (
            SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS v FROM embeddings
            WHERE embedding IS NOT NULL AND vec_id IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
        ), scored AS (
            SELECT DISTINCT q.vec_id AS query_id, c.vec_id AS vec_id,
                   list_sum(list_transform(range(1, len(c.v) + 1), lambda i: q.v[i] * c.v[i]))::BIGINT AS score
            FROM valid q JOIN valid c ON c.vec_id <> q.vec_id WHERE q.vec_id % 50 = 0
        ), ranked AS (
            SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank, vec_id, score FROM scored
        )
        SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= 5
    """,
}
