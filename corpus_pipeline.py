"""Corpus pipeline: line quality, toxicity, near-duplicates, packing; each stage is written and read again."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from sqltutor.llm import nearcopy, packing, quality, toxicity
from sqltutor.llm.common import Scratch
from sqltutor.llm.queries import tokenizer
from sqltutor.session import reach_workers
from sqltutor.store import Shelf, swept


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the line rules keep."""
    return quality.kept(docs)


def toxicity_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that a model fitted to the labelled ones among them doesn't call toxic."""
    reach_workers(spark)
    return toxicity.clean(docs, toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near-duplicates: five-word shingles, Jaccard similarity 0.8 or more."""
    reach_workers(spark)
    return nearcopy.keep_one(spark, docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of 1024-token sequences."""
    reach_workers(spark)
    return packing.packed(spark, docs, tokenizer())


STAGES = [("quality rules", quality_rules), ("toxicity", toxicity_filter), ("simhash near-dedup", near_dedup), ("packing", pack)]
#: Shingle hashes, boosted trees and token ids have no SQL; tests hold stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the last stage over all of ``documents``. What a stage left in the shared folder goes once it is written,
    and so does its predecessor."""
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        before = len(Shelf.made)
        docs = scratch.save(stage(spark, docs, sf_dir), f"stage-{k}")
        swept(spark, before)
        if k:
            scratch.drop(f"stage-{k - 1}")
    return docs
