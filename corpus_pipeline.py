"""The corpus pipeline: five stages over documents, each written as Parquet and read again as the next one's input.

All stages but the last return the input's columns, whatever their names. An empty table goes through all of them. By stage:

* language ID: rows without letters (null and empty texts too) are rejected and go; a repeated row is judged as often as it occurs.
* near duplicates: one row of each class stays, the one with the smallest id; a row that repeats an id and its words is one row; texts without
  words are never duplicates. A row with a null id always stays, since no id tells it from others.
* decontamination: rows whose text holds an item's passage go; null and empty texts and items match nothing.
* personal data: null and empty texts stay as they are; n_chars is left as it was.
* encoding: a null text is the empty one.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from graphwave.llm import bpe, decontaminate, language_id, near_dedup, pii
from graphwave.llm.common import shared_dir


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that no learned language fits go."""
    return language_id.accepted(docs, language_id.train(docs))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates stays."""
    return near_dedup.deduplicate(docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark passage go."""
    return decontaminate.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def replace_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts get surrogates for personal data."""
    return pii.pseudonymise(docs, pii.session_key(spark), spans=False)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """What remains, as token ids, with digests of the ids and of what they decode to."""
    return bpe.digests(bpe.encode(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN))


STAGES = [
    ("language_id", identify_language),
    ("near_dedup", drop_near_duplicates),
    ("decontamination", drop_leaks),
    ("pii", replace_personal_data),
    ("byte_bpe", encode),
]

#: Language models, signatures and merges are beyond SQL; tests/llm compares with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents. What lies between two stages is written to the shared checkpoint folder."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs.write.parquet(f"{folder}/{k}-{name}")
            docs = spark.read.parquet(f"{folder}/{k}-{name}")
    return docs
