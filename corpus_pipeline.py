"""The corpus pipeline: quality, near copies, secrets, mixing and encoding, each stage on all its predecessor kept.

run() chains the stages through Parquet in the folder the cluster shares, so a lost executor repeats only the
tasks of one stage.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from fieldlift.llm import bpe, mixing, near_copies, quality, secrets
from fieldlift.llm.common import table
from fieldlift.operators.stages import cleanup
from fieldlift.session import ensure_checkpoint_dir, ship

#: No SQL form: learned votes and hashed rounding have none. tests/llm checks run() against a brute-force version.
ORACLE_SQL = None


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the neighbour vote accepts."""
    ship(spark)
    return quality.keep_good(docs, table(spark, sf_dir, "labels"))


def near_copies_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component, the one with the smallest doc_id; repeated and null ids are told apart by their sets."""
    ship(spark)
    return near_copies.first_of_components(docs)


def secrets_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, secrets in their texts replaced."""
    ship(spark)
    return secrets.redact(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mixed corpus: each document as often as its source's target asks for."""
    ship(spark)
    return mixing.mix_documents(docs)


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of every row of the mix."""
    ship(spark)
    return bpe.encode_digest(docs)


STAGES = [
    ("quality classifier", quality_stage),
    ("n-gram Jaccard join", near_copies_stage),
    ("secret scans", secrets_stage),
    ("mixing sources to target weights", mixing_stage),
    ("BPE encoding and decoding", encoding_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order over the documents table; a stage's folder goes when the next one is written."""
    folder = f"{ensure_checkpoint_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
        if k:
            cleanup(spark, f"{folder}/{k - 1}")
    return docs
