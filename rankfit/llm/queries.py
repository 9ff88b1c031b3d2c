"""The subpackage's registered queries: each reads whole tables below `sf_dir` and returns its operator's full result."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from rankfit.llm import chat_format, compression_language, exact_dedup, importance, interpolated, mixing, packing, rule_forest, simhash, token_counts


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = r"\### Assistant: </turn> ok"
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], turns.schema)
    return chat_format.digests(chat_format.format_conversations(turns.unionByName(probe)))


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", simhash.hex_fingerprint(F.col("fp")).alias("fingerprint"), "component_id")


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mixture(table(spark, sf_dir, "documents"))


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.duplicate_groups(table(spark, sf_dir, "documents"))


def op5_importance(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = importance.sampled(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return found.select("doc_id", "n_features", "log_ratio", "sample_key", "kept")


def op6_interpolated(spark: SparkSession, sf_dir: str) -> DataFrame:
    return interpolated.scored(table(spark, sf_dir, "documents"))


def op7_rule_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rule_forest.judged(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(table(spark, sf_dir, "documents"))


def op10_compression_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compression_language.identified(table(spark, sf_dir, "documents"))


QUERIES = {
    "op1_chat_format": op1_chat_format,
    "op2_simhash": op2_simhash,
    "op3_mixing": op3_mixing,
    "op4_exact_dedup": op4_exact_dedup,
    "op5_importance": op5_importance,
    "op6_interpolated": op6_interpolated,
    "op7_rule_forest": op7_rule_forest,
    "op8_packing": op8_packing,
    "op9_token_counts": op9_token_counts,
    "op10_compression_language": op10_compression_language,
}
ORACLE_SQL = {"op1_chat_format": chat_format.ORACLE, "op4_exact_dedup": exact_dedup.ORACLE}
