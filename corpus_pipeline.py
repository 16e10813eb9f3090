"""The corpus pipeline: toxicity, quality, exact dedup, near dedup, packing; each stage works on all its predecessor kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sievework.llm.common import stage, table
from sievework.llm.exact_dedup import drop_copies
from sievework.llm.near_dedup import drop_alike
from sievework.llm.packing import pack_table
from sievework.llm.quality import CUT as QUALITY_CUT
from sievework.llm.quality import learn_quality, score_quality
from sievework.llm.toxicity import CUT as TOXICITY_CUT
from sievework.llm.toxicity import learn_lexicon, score_toxicity


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows below the toxicity cut."""
    lexicon = learn_lexicon(docs, table(spark, sf_dir, "labels"))
    scored = score_toxicity(docs, lexicon, name="__toxicity")
    return scored.where(F.col("__toxicity") < TOXICITY_CUT).drop("__toxicity")


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows at or above the quality cut."""
    model = learn_quality(docs, table(spark, sf_dir, "labels"))
    scored = score_quality(docs, model, name="__quality")
    return scored.where(F.col("__quality") >= QUALITY_CUT).drop("__quality")


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each set of equal texts."""
    return drop_copies(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each component of near copies: Jaccard of five-word shingles of 0.8 or more."""
    return drop_alike(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of what is left, placed in sequences."""
    return pack_table(docs)


STAGES = [("toxicity", toxicity), ("quality", quality), ("exact_dedup", exact), ("simhash_near_dedup", near), ("packing", packing)]

#: Scores of learned models, fingerprints and tokens are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, step in STAGES[:-1]:
        docs = stage(step(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
