"""Corpus pipeline over ``documents``: each stage is one operator; its result is written and read again by the next.

Stages: quality rules drop what they reject; one document of each near-duplicate group stays; documents that leak benchmark
items go; live-looking secrets are cut out of the texts; what is left is packed into sequences.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from selsketch.llm.common import Scratch, without
from selsketch.llm.decontaminate import contaminated
from selsketch.llm.near_dup import near_duplicates
from selsketch.llm.packing import pack
from selsketch.llm.quality import passing
from selsketch.llm.secrets import redacted


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the quality rules keep.  A null or empty text is rejected; each row is judged alone."""
    return passing(docs)


def near_dup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The first document of each group.  Documents without words or without id stay; repeated ids stay together."""
    return without(docs, near_duplicates(docs).where("NOT kept"))


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that leak no benchmark item.  Null and empty texts leak nothing, documents without id stay, and all rows
    of an id of which one leaks go."""
    return without(docs, contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")))


def secrets_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, live-looking secrets replaced by a mark; n_chars follows the text."""
    return redacted(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    return pack(docs)


STAGES = [
    ("quality_rules", quality_stage),
    ("near_dup", near_dup_stage),
    ("decontamination", decontamination_stage),
    ("secret_scan", secrets_stage),
    ("packing", packing_stage),
]

#: Near duplicates, tiling and packing have no SQL form; the tests hold every stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch, docs = Scratch(spark), spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
