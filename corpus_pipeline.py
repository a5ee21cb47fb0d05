"""The corpus pipeline: toxicity, SimHash near-dedup, benchmark decontamination, packing.

Every stage takes (spark, docs, sf_dir) and returns the documents it keeps, all columns of
``documents``; the last returns the pieces of the packed sequences. Each result is written as
Parquet and read again as the next stage's documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from thresher.llm import decontaminate, packing, simhash, toxicity
from thresher.llm.common import SharedTable, drop_tables, table

#: A stage on word shingles: five words, similarity 0.8 or more.
SHINGLE, SIMILARITY = 5, 0.8


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose nearest labelled examples vote against go."""
    return toxicity.keep_clean(docs, table(spark, sf_dir, "labels"))


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies, the document with the smallest id stays, one row of it.

    Texts without words and documents without an id are all kept: they are copies of nothing.
    """
    return simhash.keep_one(docs, SHINGLE, SIMILARITY)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which a benchmark window occurs go."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"), "documents")


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences of 1,024 tokens."""
    return packing.digest(packing.pack(docs))


STAGES = [
    ("toxicity", toxicity_stage),
    ("simhash_near_dedup", near_dedup_stage),
    ("benchmark_decontamination", decontamination_stage),
    ("packing", packing_stage),
]

#: Nearest examples, fingerprints and subword ids are not SQL; the tests compare with plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each stored before the next reads it.

    What a stage has stored for itself, and the stage before it, is removed once its result is stored.
    """
    others = list(SharedTable.made)
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        stored = SharedTable(stage(spark, docs, sf_dir), f"pipeline-{name}")
        drop_tables([*others, stored])
        docs = stored.read()
    return docs
