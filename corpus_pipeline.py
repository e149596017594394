"""The corpus pipeline: stages over documents, each written as Parquet and read again by the next.

1. quality: documents that the neighbour-vote classifier scores under its threshold go.
2. near-duplicates: of each SimHash group the document with the smallest id stays.
3. repeated passages: bytes of 100-byte strings that occur earlier are cut out of the texts.
4. secrets: found spans are masked.
5. packing: what is left is packed into sequences of at most 2048 tokens.

All stages but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from synthselect.llm import common, packing, quality, secrets, simhash, suffixes


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep_good(docs, common.read(spark, sf_dir, "labels"))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.near_dedup(docs)


def repeats_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return suffixes.drop_repeats(docs)


def secrets_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return secrets.mask_secrets(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs)


STAGES = [
    ("quality", quality_stage),
    ("near_duplicates", near_duplicate_stage),
    ("repeated_passages", repeats_stage),
    ("secrets", secrets_stage),
    ("packing", packing_stage),
]

#: The stages hash, encode and pack; SQL can't express them.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """STAGES in their order over documents; what a stage landed goes once its output is written."""
    docs = common.read(spark, sf_dir, "documents")
    before = len(common.LANDED)
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = common.land(docs, name)
            common.release(spark, before, keep=1)
    return docs
