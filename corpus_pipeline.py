"""A corpus pipeline of training-data operators: each stage is written as Parquet and read again as the next one's documents.

The last stage returns ``(doc_id, n_tokens, ids, ids_sha256, decoded_sha256)``, a row for every copy that the mix takes; all
others return the columns of documents.  SQL cannot express the stages; tests compare them with plain versions.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from backtrail.llm import byte_bpe, mixing, near_copies, pii
from backtrail.llm.common import remove, shared_folder, table
from backtrail.llm.quality import QualityRules

ORACLE_SQL = None


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep."""
    return QualityRules.fit(docs, table(spark, sf_dir, "labels")).keep(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, of the smallest id, of every group of texts linked by SimHash anchors and five-word shingles at Jaccard 0.8 or more."""
    return near_copies.keep_one(docs)


def redact_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with personal data and secrets replaced by their kinds; ``n_chars`` follows."""
    done = pii.redact(docs, pii.Field.train(pii.labelled_table(spark)))
    return done.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them, in training order."""
    return mixing.mix(docs)


def encode_bytes(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document."""
    return byte_bpe.digests(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, ids=True)


STAGES = [
    ("quality rules", keep_quality),
    ("near copies", drop_near_copies),
    ("personal data", redact_personal_data),
    ("mixing", mix_sources),
    ("byte BPE", encode_bytes),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what each leaves is written below the shared folder and read again.

    A stage's folder goes when the next one is written; the last one's stays, since the result is read from it.
    """
    docs, folder = table(spark, sf_dir, "documents"), f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
        if k:
            remove(spark, f"{folder}/{k - 1}")
    return docs
