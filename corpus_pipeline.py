"""A corpus pipeline: five stages over `documents`, each on all that the one before it kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from rankfit.llm import exact_dedup, importance, mixing, packing, simhash
from rankfit.session import drop_table, new_table


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that importance resampling towards labelled good text keeps."""
    return importance.accepted(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents with equal normalised texts, the one with the smallest id."""
    return exact_dedup.keep_first(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group linked by similar sets of five-word shingles (0.8 and above), the document with the smallest id."""
    return simhash.keep_one_of_similar(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix at the sources' targets: documents once for each epoch they are taken in."""
    return mixing.mixed(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents and their places in sequences."""
    return packing.pack(docs)


STAGES = [("quality_classifier", quality), ("exact_dedup", exact), ("simhash", near), ("mixing", mix), ("packing", pack)]

#: SQL has neither the classifier's sample, XXH64 of shingles nor the vocabulary; tests compare with plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over `documents`; what passes between them is Parquet in the shared folder."""
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for name, stage in STAGES[:-1]:
        path = new_table(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        if before:
            drop_table(spark, before)
        before = path
    # The last stage stores what it needs of its input before it returns.
    out = STAGES[-1][1](spark, docs, sf_dir)
    drop_table(spark, before)
    return out
