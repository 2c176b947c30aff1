"""The queries opN_<name> and the pipeline, as __spark_entry__.py registers them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rotahash.llm import decontaminate, embedding_join, jaccard_join, language_id, licenses, lm_scoring, mixing, oracle, suffix_dedup, tokenfiles, toxicity


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.deduplicate(table(spark, sf_dir, "documents"))


def op2_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scoring.score(table(spark, sf_dir, "documents"))


def op3_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.jaccard_join(table(spark, sf_dir, "documents"))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix(mixing.sized(table(spark, sf_dir, "documents")))
    return mixed.select("doc_id", "size", "source_size", "target", "taken")


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify(table(spark, sf_dir, "documents"))


def op7_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(table(spark, sf_dir, "documents"))


def op8_embedding_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_join.embedding_join(table(spark, sf_dir, "embeddings"))


def op9_tokenfiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenfiles.read(*tokenfiles.write(table(spark, sf_dir, "documents"), tokenizer_path()))


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = toxicity.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return scored.select("doc_id", "p_quality", "p_toxic", F.col("rejected").alias("toxic"))


QUERIES = {f.__name__: f for f in (op1_suffix_dedup, op2_lm_scoring, op3_jaccard_join, op4_mixing, op5_decontaminate, op6_language_id, op7_licenses, op8_embedding_join, op9_tokenfiles, op10_toxicity)}

#: The other operators are trained, encode or cut by Spark's hash; tests/llm compares them with brute force.
ORACLE_SQL: dict[str, str] = {
    "op1_suffix_dedup": oracle.SUFFIX_DEDUP,
    "op3_jaccard_join": oracle.JACCARD_JOIN,
    "op7_licenses": oracle.licenses(licenses.TEMPLATES, licenses.THRESHOLD),
    "op8_embedding_join": oracle.EMBEDDING_JOIN,
}
