"""A training corpus from raw documents, in five stages.

``STAGES`` lists them in order. Each takes the documents that its predecessor kept, decides about all of
them, and returns the columns of documents; the last one returns token ids. Stages are written as Parquet
and read again, so a lost executor costs tasks and never an earlier stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from groupflow.llm import decontamination, minhash, piece_tokens, secrets, toxicity
from groupflow.llm.folds import held_out
from groupflow.storage import materialize


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model, trained on the labelled training fold, does not reject.

    Null and empty texts have no sentence, score 0 and stay. Rows that repeat are judged each for itself. A score of
    just 0.5 rejects. Without labels of both kinds, or without rows, nothing is rejected.
    """
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = toxicity.train(docs, labels.filter(~held_out()))
    return toxicity.keep_clean(docs, model)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest doc_id of each group of documents linked at a shingle similarity of 0.8 or more.

    Null, empty and white texts and rows with a null doc_id stay; of rows that repeat a doc_id one stays. No rows, no result.
    """
    return minhash.drop_near_duplicates(docs, minhash.MinHashParams(threshold=80))


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a passage of the benchmark.

    Null and empty texts, and rows with a null doc_id, stay. Rows that repeat a doc_id go or stay together. Without
    benchmark items, or with none but short ones, all stay.
    """
    return decontamination.drop_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, secrets in their texts replaced, overlapping ones together.

    A null or empty text stays as it is. Repeated rows are changed alike.
    """
    return secrets.redact(docs)


def tokenize(spark: SparkSession, docs: DataFrame, sf_dir: str, model: str | None = None) -> DataFrame:
    """``doc_id, n_tokens, ids, decoded_sha256``: ids of each document and a digest of their decoding.

    A null text is an empty one and has no ids. Repeated rows give repeated results, no rows none.
    """
    if model is None:
        import public_tokenizers

        model = str(public_tokenizers.path("piece_bpe_32k.model"))
    # a small cache: the workers of earlier stages share the memory
    return piece_tokens.tokenize(docs, model, cached=50_000).select(
        "doc_id", F.size("ids").cast("long").alias("n_tokens"), "ids", F.sha2("decoded", 256).alias("decoded_sha256")
    )


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_benchmark_leaks),
    ("secrets", redact_secrets),
    ("tokens", tokenize),
]

#: Learned models and tokenizers have no SQL; tests/llm holds each stage against a brute-force version on the smallest tables.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return docs
