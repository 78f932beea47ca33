"""The corpus pipeline: five stages over documents, each written before the next reads it.

Every stage takes the whole output of the one before.  All but the last return
the columns of ``documents``; the last returns packed pieces.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsepairs.llm import near_duplicates, packing, pairwise_quality, secret_scan, shared, toxicity


def _labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose pairwise quality score reaches the cut."""
    scorer = pairwise_quality.fit(docs, _labels(spark, sf_dir))
    scored = pairwise_quality.score(docs, scorer, "__score")
    return scored.where(F.col("__score") >= pairwise_quality.CUT).drop("__score")


def toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity stays below the threshold of their language."""
    model = toxicity.fit(docs, _labels(spark, sf_dir))
    scored = toxicity.score(docs, model, "__score")
    return scored.where(F.col("__score") < toxicity.threshold(model)).drop("__score")


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, of the smallest id, from each class of near copies; a repeated row stays once, another text of an id stays."""
    return near_duplicates.without_copies(docs)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents with their secrets masked; ``n_chars`` follows the new text."""
    return secret_scan.mask_secrets(docs).withColumn("n_chars", F.length("text").cast("long"))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of 1024 tokens."""
    return packing.pack_documents(docs)


STAGES = [("quality", quality), ("toxicity", toxic), ("near copies", near_copies), ("secrets", secrets), ("packing", packed)]

#: Learned stages and tokenizers have no SQL form; tests hold the pipeline against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written as Parquet and read by the next."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = shared.written(stage(spark, docs, sf_dir), f"stage-{name.replace(' ', '-')}")
    return docs
