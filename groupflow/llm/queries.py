"""The registered queries of these operators, with production parameters, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from groupflow.llm import (
    decontamination,
    language,
    minhash,
    piece_tokens,
    secrets,
    sharding,
    token_files,
    toxicity,
    url_filter,
    vector_graph,
)
from groupflow.llm.folds import held_out
from groupflow.llm.sql import op2_sql, op4_sql, op7_sql


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _tokenizer(name: str) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    dictionaries = language.train(docs.filter(~held_out()))
    return language.identify(docs, dictionaries).select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "rejected")


def op2_vector_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_graph.near_duplicates(_table(spark, sf_dir, "embeddings"))


def embedding_recall_audit(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = _table(spark, sf_dir, "embeddings")
    return vector_graph.audit_recall(vectors, vector_graph.near_duplicates(vectors))


def op3_token_files(spark: SparkSession, sf_dir: str, tokenizer: str | None = None) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    return token_files.read(token_files.write(docs, tokenizer or _tokenizer("byte_bpe_50k.json")))


def op4_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(_table(spark, sf_dir, "documents"))


def op5_sentencepiece(spark: SparkSession, sf_dir: str, model: str | None = None) -> DataFrame:
    return piece_tokens.digests(_table(spark, sf_dir, "documents"), model or _tokenizer("piece_bpe_32k.model"))


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.find_leaks(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(_table(spark, sf_dir, "pages"))


def op8_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets.scan_documents(_table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2("base_spans", 256).alias("base_sha256"), "spans", "bounded")


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = _table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels")
    model = toxicity.train(docs, labels.filter(~held_out()))
    return toxicity.score(docs, model).select("doc_id", held_out().alias("held_out"), "score", "predicted", "offending")


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign(_table(spark, sf_dir, "documents"), 16)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_language_id,
        op2_vector_graph,
        op3_token_files,
        op4_minhash,
        op5_sentencepiece,
        op6_decontamination,
        op7_url_filter,
        op8_secret_scan,
        op9_toxicity,
        op10_sharding,
        embedding_recall_audit,
    )
}

#: Queries that SQL can express; the others are tested against brute force, round trips or held-out rows.
ORACLE_SQL: dict[str, str] = {"op2_vector_graph": op2_sql(), "op4_minhash": op4_sql(), "op7_url_filter": op7_sql()}
