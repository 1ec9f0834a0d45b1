"""Corpus pipeline over ``documents``: five stages, each written as Parquet and read by the next.

Stage by stage: documents that the quality classifier rejects go; of equal texts one document stays; of
near copies one stays; documents that hold benchmark passages go; what is left is encoded by byte-level
BPE and decoded again, and each document's token count and digests are returned.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from gnn_delta.llm import bpe, classifiers, decontaminate, exact_dedup, simhash
from gnn_delta.llm.common import forget, written
from gnn_delta.llm.queries import tokenizer_path
from gnn_delta.plans.session import ship


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return classifiers.keep_quality(docs, ship(spark).read.parquet(f"{sf_dir}/labels.parquet"))


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.dedup(docs, keep="largest")


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return simhash.dedup(docs)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.clean(docs, ship(spark).read.parquet(f"{sf_dir}/benchmark.parquet"))


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    return bpe.round_trip(docs, tokenizer_path())


STAGES = [
    ("quality classifier", quality),
    ("exact dedup", exact),
    ("SimHash near-dedup", near),
    ("benchmark decontamination", decontaminated),
    ("BPE encoding and decoding", encoded),
]
#: the classifier is fitted, so SQL cannot give these rows; tests/llm checks each stage by brute force
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; the tables between stages lie in the shared folder until read."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    before = None
    for k, (_, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if k == len(STAGES) - 1:
            return out
        docs = written(out, f"stage{k}")
        if before is not None:
            forget(before)
        before = docs
    return docs
