"""A corpus pipeline of five stages, each written as Parquet and read again as the next one's documents."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from rootfinal.llm import bpe_codec, mixing, near_copies, personal_data, quality
from rootfinal.llm.queries import tokenizer_path
from rootfinal.llm.shared import finished, intermediates, shared_dir, table


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the current policy keeps."""
    return quality.good(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies."""
    return near_copies.drop_copies(spark, docs)


def redact_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data replaced by its kind."""
    return personal_data.redact_column(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Copies of documents as the mix takes them, by training position."""
    return mixing.mix(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every copy."""
    return bpe_codec.encode_ids(docs, tokenizer_path("word_bpe_49k.json"), ["doc_id", "source"])


STAGES = [("quality_rules", quality_rules), ("near_dedup", near_dedup), ("redact_personal_data", redact_personal_data), ("mix_sources", mix_sources), ("encode", encode)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str, folder: str | None = None) -> DataFrame:
    """The last stage's rows. With a shared `folder`, stages that a run before this one finished there are read, not run again.

    What a stage wrote on its way goes once its result is written.
    """
    docs = table(spark, sf_dir, "documents")
    folder = folder or f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for i, (name, stage) in enumerate(STAGES):
        path = f"{folder}/{i}-{name}"
        if not finished(spark, path):
            with intermediates(spark):
                stage(spark, docs, sf_dir).write.mode("overwrite").parquet(path)
        docs = spark.read.parquet(path)
    return docs
