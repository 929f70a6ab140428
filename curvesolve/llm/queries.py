"""Registered queries of the corpus operators; the operators are applied with production parameters to whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, chat, itq, line_dedup, mixing, nbsvm, pii, quality_rules, secrets, simhash
from ._common import table

TOKENIZER = "word_bpe_49k.json"


def tokenizer_path(name: str = TOKENIZER) -> str:
    """The place of a public vocabulary file, the same on every executor."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.apply_rules(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, lines cut, and the length and digest of what is left of each document."""
    out = line_dedup.dedup_corpus(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_gone", F.length("text").alias("n_left"), F.sha2(F.col("text").cast("binary"), 256).alias("text_sha256"))


def op3_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digest_documents(table(spark, sf_dir, "documents"), tokenizer_path())


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op5_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.format_turns(table(spark, sf_dir, "conversations"), chat.TOOLS)


def chat_tool_calls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same over conversations whose turns are made calls and results, as the given ones hold none."""
    return chat.format_turns(chat.as_tool_calls(table(spark, sf_dir, "conversations")), chat.TOOLS)


def op6_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digest(pii.find_personal_data(table(spark, sf_dir, "documents")))


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"), weights=mixing.TARGETS).select("doc_id", "leaf", "copies")


def op8_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return nbsvm.score_documents(docs, nbsvm.train(docs, table(spark, sf_dir, "labels")))


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.digest(secrets.find_secrets(table(spark, sf_dir, "documents")))


def op10_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return itq.links(table(spark, sf_dir, "embeddings"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = (op1_quality_rules, op2_line_dedup, op3_bpe, op4_simhash, op5_chat_format, op6_personal_data, op7_mixing,
             op8_quality_classifier, op9_secrets, op10_embedding_dedup, pipeline, chat_tool_calls)
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    from .oracles import SQL

    return dict(SQL)
