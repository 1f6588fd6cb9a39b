"""The ten operators as queries over their whole tables, with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe_transducer import round_trip_digests
from .embedding_dedup import SQL as EMBEDDING_DEDUP_SQL
from .embedding_dedup import near_duplicate_vectors
from .encoding import public_path
from .exact_dedup import SQL as EXACT_DEDUP_SQL
from .exact_dedup import exact_duplicates
from .language_id import predict
from .near_dedup import SQL as NEAR_DEDUP_SQL
from .near_dedup import near_duplicates
from .packing import pack_documents
from .quality import resample
from .shared import load
from .token_files import token_file_report
from .toxicity import score_documents
from .url_filter import judge_urls
from .url_filter import sql as url_sql


def op1_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(load(spark, sf_dir, "documents"), words_each=2)


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_documents(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"))


def op3_lexical_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(load(spark, sf_dir, "documents"), public_path("byte_bpe_50k.json"), added=True)


def op4_bpe_transducer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip_digests(load(spark, sf_dir, "documents"), public_path("byte_bpe_multi_50k.tiktoken"))


def op5_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicate_vectors(load(spark, sf_dir, "embeddings"))


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_duplicates(load(spark, sf_dir, "documents"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return resample(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"))


def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    # Flows are rounded to what no order of summation changes.
    return judge_urls(load(spark, sf_dir, "pages")).withColumns({c: F.round(c, 9) for c in ("trust", "distrust")})


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return predict(load(spark, sf_dir, "documents"), public_path("piece_bpe_32k.model"))


def op10_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_file_report(load(spark, sf_dir, "documents"), public_path("byte_bpe_50k.json"), added=True)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_near_dedup": op1_near_dedup,
    "op2_toxicity": op2_toxicity,
    "op3_lexical_packing": op3_lexical_packing,
    "op4_bpe_transducer": op4_bpe_transducer,
    "op5_embedding_dedup": op5_embedding_dedup,
    "op6_exact_dedup": op6_exact_dedup,
    "op7_quality": op7_quality,
    "op8_url_filter": op8_url_filter,
    "op9_language_id": op9_language_id,
    "op10_token_files": op10_token_files,
}

ORACLE_SQL: dict[str, str] = {
    "op1_near_dedup": NEAR_DEDUP_SQL,
    "op5_embedding_dedup": EMBEDDING_DEDUP_SQL,
    "op8_url_filter": url_sql(),
    "op6_exact_dedup": EXACT_DEDUP_SQL,
}
