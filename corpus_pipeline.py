"""The corpus pipeline: quality, exact dedup, near dedup, mixing, tokens; each stage over all that the last one kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqcount.llm import bpe, exact_dedup, mixing, quality_knn, simhash
from seqcount.llm.common import fresh
from seqcount.session import delete_folder, new_folder, shipped

#: A document goes if its score is below this: label 0 is then the likelier by the vote.
REJECT_BELOW = 0.5


@shipped
def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that the classifier doesn't reject. It's fitted on labelled rows of what comes in."""
    model = quality_knn.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    (score,) = fresh(docs, "score")
    return quality_knn.with_scores(docs, model, name=score).where(F.col(score) >= REJECT_BELOW).drop(score)


@shipped
def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts, the row with the largest id."""
    return exact_dedup.drop_exact_copies(docs, keep="largest")


@shipped
def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies (2 bits of SimHash, or similarity 0.8 on five words), the row with the smallest id."""
    return simhash.drop_near_copies(docs)


@shipped
def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each row as often as its source's rate says."""
    return mixing.mix_sources(docs)


@shipped
def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of ids and of the decoded bytes, one row for each copy."""
    return bpe.token_digests(docs)


STAGES = [("quality", quality), ("exact_dedup", exact), ("near_dedup", near), ("mixing", mix), ("bpe", tokens)]

#: Neighbour votes and byte-pair merges are beyond SQL; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result is written and read again as the next one's input, and deleted after it.

    The last stage's result stays in its folder, for the frame that is returned reads it.
    """
    docs, folder, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), new_folder(spark, "pipeline"), None
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        if before:
            delete_folder(spark, before)
        before = f"{folder}/{name}"
    return docs
