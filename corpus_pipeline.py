"""A training corpus from ``documents``: language, near duplicates, repeated passages, secrets, packing.

Each stage takes all rows its predecessor kept and is written and read again before the next one.
Rows go only in the first two stages: texts without any language, and near duplicates but one of each class.
Later stages change texts (repeated passages, secrets) and keep every row, nulls and empty texts too.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from codeschema.llm import language_id, near_dedup, packing, secret_scan, substring_dedup
from codeschema.llm.base import free_name, table, written


def languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents in which no language is found."""
    path = public_tokenizers.path("piece_bpe_32k.model")
    model = language_id.train(docs, path)
    if not model[0]:
        return docs
    pred, score = free_name(docs, "lang_pred"), free_name(docs, "lang_score")
    found = language_id.identify(docs, model, path, keep=True, pred_col=pred, score_col=score)
    return found.where(f"`{pred}` <> 'und'").select(*[f"`{c}`" for c in docs.columns])


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each class of near duplicates: the one with the least doc_id."""
    return near_dedup.one_of_each(docs)


def passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes passages of 20 words or more that an earlier document, or the same one, already has."""
    return substring_dedup.cleaned(docs)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces secrets in the texts."""
    return secret_scan.redacted(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of 1024 tokens."""
    return packing.pack(docs, public_tokenizers.path("byte_bpe_50k.json"), window=1024, end_id=0)


STAGES = [("language_id", languages), ("near_dedup", near_duplicates), ("substring_dedup", passages), ("secret_scan", secrets), ("packing", packed)]
#: Fitted models and identifiers of a tokenizer are beyond SQL; tests compare ``run`` with a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
