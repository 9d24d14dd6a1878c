"""The queries of this subpackage, with the parameters they run with in production."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import language_id, media_ogg, near_dedup, packing, piece_codec, secret_scan, substring_dedup, token_store, topk_search, toxicity
from .base import scratch, table


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.predictions(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), window=1024, end_id=0)


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.predictions(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.digests(substring_dedup.deduplicated(table(spark, sf_dir, "documents")))


def op5_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch(spark, "token-store")
    token_store.write_store(table(spark, sf_dir, "documents"), path, public_tokenizers.path("word_bpe_49k.json"), end_id=2)
    return token_store.read_store(spark, path)


def op6_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return topk_search.exact_topk(vectors, vectors.where("vec_id % 100 = 0"), k=10, scale=1024.0)


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.digests(secret_scan.find_secrets(table(spark, sf_dir, "documents")))


def op8_media_ogg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_ogg.digests(media_ogg.ogg_media(table(spark, sf_dir, "documents")))


def op9_piece_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_codec.digests(piece_codec.encode_column(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model")))


def op10_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_dedup.classes(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "class_id", F.col("doc_id").eqNullSafe(F.col("first.doc_id")).alias("is_first"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {
    "op1_toxicity": op1_toxicity,
    "op2_packing": op2_packing,
    "op3_language_id": op3_language_id,
    "op4_substring_dedup": op4_substring_dedup,
    "op5_token_store": op5_token_store,
    "op6_topk_search": op6_topk_search,
    "op7_secret_scan": op7_secret_scan,
    "op8_media_ogg": op8_media_ogg,
    "op9_piece_codec": op9_piece_codec,
    "op10_near_dedup": op10_near_dedup,
    "pipeline": pipeline,
}
ORACLES = {"op4_substring_dedup": substring_dedup.ORACLE, "op6_topk_search": topk_search.ORACLE}
