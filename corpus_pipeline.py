"""Corpus pipeline: quality classifier, quality rules, near-duplicate removal, packing.

Each stage takes ``(spark, docs, sf_dir)`` and works on everything its predecessor kept; between stages ``docs`` is
written as Parquet and read again.  All stages but the last return the columns of ``documents``, whatever else they
are called; null texts are empty, null and repeated ids are rows like any other, and an empty table gives no piece.
"""

from __future__ import annotations

import public_tokenizers
from delimscan.llm import cascade, cotrain, packing, simhash
from delimscan.llm.common import durable
from pyspark.sql import DataFrame, SparkSession


def classify(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the co-trained classifier keeps."""
    return cotrain.kept(docs, cotrain.fit_model(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that no rule of the cascade rejects."""
    return cascade.kept(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of texts within three bits: the narrower stage, for callers that want no other copies removed."""
    return simhash.keep_one(docs, least=None)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of texts within three bits, or with a Jaccard similarity of their five-word shingles of 0.8 or more."""
    return simhash.keep_one(docs, least=0.8, shingle=5)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of packed sequences."""
    return packing.pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"), end_id=1, capacity=2048, room=300_000, slice_bytes=1 << 20)  # other stages' memory is still held by the executors


STAGES = [("quality classifier", classify), ("quality rules", rules), ("near duplicates", near_copies), ("packing", pack)]
ORACLE_SQL = None  # no SQL for a trained classifier or for packing; tests/llm holds each stage against brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = durable(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
