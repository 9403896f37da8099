"""The corpus pipeline: five stages over documents, each written as Parquet and read again by the next.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from compresslab.llm import bpe, decontaminate, near_copies, secrets, toxicity
from compresslab.llm import common as C


def without_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """docs without toxic rows (score 0.5 and more). Null and empty texts score the intercept alone and stay unless most labels are
    toxic; repeated rows go or stay together; very long texts are scored whole; no labels: all stay; extra columns stay."""
    return toxicity.drop_toxic(docs, toxicity.fit(spark, docs, C.table(spark, sf_dir, "labels")))


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """docs with one row of each class of copies and near copies: the smallest doc_id. Rows with a null doc_id or text stay; rows
    repeated in doc_id and text stay once; a doc_id with several texts loses only those with a class mate; extra columns stay."""
    return near_copies.keep_one(docs)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """docs without the rows in which a benchmark item is found, verbatim, quoted or by a template. Rows with a null doc_id or text
    stay; repeated rows go together; items under five words and an empty benchmark find nothing; extra columns stay."""
    return decontaminate.drop_contaminated(docs, C.table(spark, sf_dir, "benchmark"))


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows of docs; secrets in texts are replaced by a mark, whatever their length, and n_chars follows. Null and empty texts
    stay as they are; repeated rows change alike; extra columns stay."""
    return secrets.redact(docs)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every row of docs, in no order. Null texts count as empty and have no tokens;
    repeated rows are encoded each; very long texts are chunked; null doc_ids stay null; no other column is passed on."""
    return bpe.encode(docs)


STAGES = [
    ("toxicity", without_toxic),
    ("near_copies", without_near_copies),
    ("decontamination", without_benchmark),
    ("secrets", without_secrets),
    ("encoding", encoded),
]

# trained models, sampling and tokenising are beyond SQL; tests compare with a brute-force version
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = C.table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = C.materialize(docs, f"stage-{name}")
    return docs
