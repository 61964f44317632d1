"""The queries over the given tables: every operator, with production parameters, on its whole table."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, bytebpe, exact_dedup, langid, lm, minhash, packing, pii, sharding, token_counts


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def _rest(of: int, is_: int) -> Column:
    """Whether the checksum of doc_id as text leaves this remainder; a null doc_id leaves none."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % of == is_, F.lit(False))


def op1_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(_documents(spark, sf_dir), shingle=4, percent=80)


def op2_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm.score_documents(_documents(spark, sf_dir), _rest(5, 1))


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(_documents(spark, sf_dir), bytebpe.vocabulary_path("piece_bpe_32k.model"))


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(_documents(spark, sf_dir))


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_documents(spark, sf_dir), 1024)


def op6_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.nearest(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), F.col("vec_id") % 20 == 0, 20)


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = langid.identify(_documents(spark, sf_dir), ~_rest(3, 1))
    return found.select("doc_id", _rest(3, 1).alias("held_out"), "lang_pred", "score", "cross_entropy", "accepted")


def op8_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bytebpe.digests(_documents(spark, sf_dir), bytebpe.vocabulary_path("byte_bpe_multi_50k.tiktoken"))


def op9_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.pseudonymise(_documents(spark, sf_dir), pii.session_key(spark)).select("doc_id", "text", "n_found", "n_replaced")


def op10_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.assign_shards(_documents(spark, sf_dir), 16)
    return placed.withColumns({"law": F.lit("bytes"), "grown_shard": F.lit(None).cast("int")})


QUERIES = [op1_near_duplicates, op2_lm_scores, op3_token_counts, op4_exact_dedup, op5_packing, op6_nearest, op7_language, op8_byte_bpe, op9_pseudonyms, op10_shards]


def queries() -> dict:
    return {f.__name__: f for f in QUERIES}


def oracle_sql() -> dict[str, str]:
    return {
        "op4_exact_dedup": """
            WITH d AS (SELECT doc_id, sha256(coalesce(text, '')) AS text_sha256 FROM documents)
            SELECT doc_id, max(doc_id) OVER g AS keep_id, count(*) OVER g AS group_size, doc_id = max(doc_id) OVER g AS kept, text_sha256
            FROM d WINDOW g AS (PARTITION BY text_sha256)""",
        "op6_nearest": """
            WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings
                       WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0
                         AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
            s AS (SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.e, c.e) AS score
                  FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.e) = len(c.e) WHERE q.vec_id % 20 = 0),
            r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS "rank" FROM s)
            SELECT query_id, "rank", vec_id, score FROM r WHERE "rank" <= 20""",
    }
