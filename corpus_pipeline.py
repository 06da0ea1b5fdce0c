"""A corpus pipeline of four stages: host quality rules, toxicity, near duplicates, packing.

Every stage reads all that the one before kept.  The filters return the columns of ``documents`` as they were; the last
stage returns the packed pieces.  SQL cannot express the classifier, so there is no oracle; tests compare the
stages with brute-force versions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from patternldp.llm.host_quality import keep_good
from patternldp.llm.ngram_join import keep_firsts
from patternldp.llm.packing import pack
from patternldp.llm.scratch import discard, materialise, table
from patternldp.llm.toxicity import keep_clean
from patternldp.shipping import ship


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and whose host passes."""
    ship(spark)
    return keep_good(docs)


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the convolutional classifier does not call toxic."""
    ship(spark)
    return keep_clean(docs, table(spark, sf_dir, "labels"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of sets of five-word shingles that are linked at a similarity of 0.8."""
    ship(spark)
    return keep_firsts(docs, k=5, num=80, den=100)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 2048 tokens with their sequence and place."""
    ship(spark)
    return pack(docs)


STAGES = [("quality rules", quality), ("toxicity", toxicity), ("n-gram Jaccard join", near_duplicates), ("best-fit packing", packing)]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what a stage keeps is written and reread."""
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        before, docs = docs, stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = materialise(docs, f"stage-{i}")
            if i:
                discard(before)
    return docs
