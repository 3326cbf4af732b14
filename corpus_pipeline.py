"""A training corpus from raw documents, in five stages, each written as a table and read again.

toxicity: documents that score as toxic go. near_duplicates: of each group of near copies one document stays. pii: marks
replace personal data in the texts. mixing: sources are repeated or thinned to their target weights. packing: documents
become pieces with their token ids and places in sequences, the only stage whose columns are not those of documents.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from taskmesh.llm.minhash import drop_near_duplicates
from taskmesh.llm.mixing import mix
from taskmesh.llm.packing import pack_documents
from taskmesh.llm.pii import redact
from taskmesh.llm.toxicity import filter_toxic
from taskmesh.llm.words import release
from taskmesh.sources import load, materialise, relieve, ship_package

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return filter_toxic(docs, load(spark, sf_dir, "labels", ["doc_id", "toxic"]))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_near_duplicates(docs)


def pii(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return redact(docs)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mix(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack_documents(docs, with_ids=True)


STAGES: list[tuple[str, Stage]] = [
    ("toxicity", toxicity),
    ("near_duplicates", near_duplicates),
    ("pii", pii),
    ("mixing", mixing),
    ("packing", packing),
]

#: Learned scores, shingles and tokenizers are beyond SQL; the tests hold the stages against brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of ``sf_dir``."""
    ship_package(spark)
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), f"pipeline-{name}")
        release()  # a stage's learned models and plans are not the next one's load
        relieve(spark, 0.0)
    return docs
