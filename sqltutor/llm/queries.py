"""Queries over the corpus operators and, where SQL can say the same, their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..session import reach_workers
from . import bpe, ogg, packing, quality, repair, sharding, simhash, toxicity, urlrules, warc


def tokenizer() -> str:
    """Where the public byte-level vocabulary file lies on this machine; every worker has it at the same place."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    reach_workers(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(spark, _table(spark, sf_dir, "documents"))


def op2_ogg_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ogg.features(_table(spark, sf_dir, "documents"))


def op3_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.verdicts(_table(spark, sf_dir, "documents"))


def op4_warc_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.archive_digest(spark, _table(spark, sf_dir, "pages"))


def op5_label_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.sharded(spark, _table(spark, sf_dir, "documents"))


def op6_speculative_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(_table(spark, sf_dir, "documents"), tokenizer())


def op7_boosted_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    return toxicity.scored(docs, toxicity.fit(docs, _table(spark, sf_dir, "labels")))


def op8_concat_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(spark, _table(spark, sf_dir, "documents"), tokenizer())


def op9_url_association_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlrules.judged(spark, _table(spark, sf_dir, "pages"), _table(spark, sf_dir, "labels"))


def op10_repair_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repair.stored(spark, _table(spark, sf_dir, "documents"), tokenizer())


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpus_pipeline import run

    reach_workers(spark)
    return run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (
    op1_simhash_near_dedup, op2_ogg_media, op3_line_quality, op4_warc_index, op5_label_sharding, op6_speculative_bpe,
    op7_boosted_toxicity, op8_concat_packing, op9_url_association_rules, op10_repair_token_files, pipeline)}
SQL = {"op3_line_quality": quality.oracle()}
