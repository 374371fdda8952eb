"""Training-corpus pipeline: four stages over documents, each written and read again.

A stage takes (spark, docs, sf_dir), works on all its predecessor kept, and
returns documents in the columns it was given; only the last returns pieces.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from vintage.llm import minhash_dedup, packing, quality_rules, toxicity
from vintage.llm.common import shared_dir, table
from vintage.sources.tables import delete, release, scratch


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep."""
    trees = quality_rules.train(docs, table(spark, sf_dir, "labels"))
    return quality_rules.judge(docs, trees).where("kept").select(*docs.columns)


def toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that aren't toxic."""
    grammar = toxicity.learn(docs, table(spark, sf_dir, "labels"))
    return toxicity.judge(docs, grammar).where("toxic = 0").select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates (word shingles alike to 0.8 or more): the one with the least id.

    Rows that repeat an id stay as they are if that id is kept.
    """
    classes = minhash_dedup.near_duplicates(docs.select("doc_id", "text"), percent=80)
    gone = classes.where("not kept").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces of the documents with their place in a sequence."""
    return packing.pack(packing.pieces(docs.select("doc_id", "text")))


STAGES = [("quality rules", quality), ("toxicity", toxic), ("near-duplicates", near_dedup), ("packing", pack)]

#: Trees, a learned grammar and token ids are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what a stage returns is written as Parquet in the shared folder.

    A stage's scratch tables, and the rows of the stage before, go once its own rows are written.
    """
    docs = table(spark, sf_dir, "documents")
    base = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES):
        since = len(scratch())
        stage(spark, docs, sf_dir).write.parquet(f"{base}/{k}")
        docs = spark.read.parquet(f"{base}/{k}")
        release(spark, since)
        if k:
            delete(spark, f"{base}/{k - 1}")
    return docs
