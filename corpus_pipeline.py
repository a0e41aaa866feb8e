"""The training-data pipeline: each stage works on all that the one before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from gramdist.llm import bloom_dedup, mil_toxicity, mixing, packing, shingle_join
from gramdist.llm.common import written


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose score stays below 0.5, the model being fitted to the labels of all documents. Each row is
    judged by its own text, whatever its id."""
    model = mil_toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return mil_toxicity.clean(docs, model)


def exact_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each text."""
    return bloom_dedup.distinct_texts(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of texts linked by five-word Jaccard 0.8 or more: the one with the smallest id. The
    Gray-order index over SimHash fingerprints proposes links, which are verified; an exact search finds the rest. Ids
    are taken to be unique; rows that share one stay or go together, and a row without an id stays."""
    classes = shingle_join.near_copies(docs)
    gone = written(classes.where("doc_id != component_id").select("doc_id").distinct())
    return bloom_dedup.without_ids(docs, gone)


def mixing_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix: a document appears as often as it is taken."""
    return mixing.mixed(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Binary pieces, each a sequence."""
    return packing.pack(docs, packing.default_tokenizer())


STAGES = [("toxicity", toxicity), ("exact_dedup", exact_dedup), ("near_dedup", near_dedup), ("mix_sources", mixing_sources), ("pack_binary", pack)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = written(docs)
    return docs
