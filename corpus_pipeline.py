"""Corpus pipeline: quality, toxicity, near duplicates, benchmark passages, tokens.

Each stage works on all that the one before kept and returns the columns of ``documents``; the last one encodes
what is left.  Near duplicates share five-word shingles at a similarity of 0.8 or more.

Defined results: null and empty texts are judged as texts without words and, if a filter keeps them, stay (they are no
near copies of each other); rows with a null doc_id are judged by their text and are copies of nothing; repeated rows
are judged alike; other columns, whatever their names, pass untouched; an empty table gives no row.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from graphdelta.llm import bpe, decontaminate, jaccard, quality, toxicity
from graphdelta.llm.common import saved, shared_dir, table  # noqa: F401

#: SQL cannot express the learned stages; ``tests/llm/test_pipeline.py`` holds each against a plain version.
ORACLE_SQL = None


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier keeps, with all their columns."""
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    return quality.kept(docs, model)


def not_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity classifier keeps, with all their columns."""
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    return toxicity.kept(docs, model)


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the least id of each group of near copies; texts without words and rows without id stay."""
    groups = jaccard.join(docs, 5, 80).filter("n_shingles > 0 and doc_id is not null and doc_id != component_id").select("doc_id").distinct()
    return docs.join(groups, "doc_id", "left_anti").select(*docs.columns)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no benchmark passage is found, with all their columns."""
    return decontaminate.clean(docs, decontaminate.build(table(spark, sf_dir, "benchmark")))


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of what is left."""
    return bpe.round_trip(docs, bpe.vocabulary("byte_bpe_50k.json"))


STAGES = [
    ("quality", good_quality),
    ("toxicity", not_toxic),
    ("near_copies", without_near_copies),
    ("benchmark", without_benchmark),
    ("bpe", encoded),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each result is written as Parquet in the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    folder = f"{shared_dir(spark)}/graphdelta/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES:
        path = f"{folder}/{name}"
        kept = stage(spark, docs, sf_dir)
        kept.write.parquet(path)
        docs = spark.read.schema(kept.schema).parquet(path)
    return docs
