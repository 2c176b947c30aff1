"""From raw documents to token files: toxic texts out, one text of each near-duplicate group, benchmark passages out, sources mixed, ids written.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame. ``run`` writes what a stage returns as
Parquet on shared storage and reads it back as the next one's docs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rotahash.llm import decontaminate, jaccard_join, mixing, tokenfiles, toxicity
from rotahash.llm.durable import free_name, new_folder
from rotahash.llm.queries import table, tokenizer_path


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.reject(docs, table(spark, sf_dir, "labels"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard_join.keep_one(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each copy that the mix takes: documents the mix does not reach go, others stand up to three times.

    Rows that repeat doc_id, source and text share the least of their counts, so that they stay as many as they were;
    different texts of one doc_id, null among them, have counts of their own.
    """
    times = F.when(F.col("taken") > 0, F.expr("taken div size")).otherwise(0).cast("int")
    own, key, print_, count, copy = (free_name(docs, x) for x in ("own", "key", "print", "times", "copy"))
    docs_ = docs.withColumn(own, F.xxhash64("source", "text"))
    sized = mixing.sized(docs_, ("doc_id", "source", own))
    mixed = mixing.mix(sized).groupBy(F.col("doc_id").alias(key), F.col(own).alias(print_)).agg(F.min(times).alias(count)).where(F.col(count) > 0)
    joined = docs_.join(mixed, docs_["doc_id"].eqNullSafe(mixed[key]) & (docs_[own] == mixed[print_]))
    return joined.withColumn(copy, F.explode(F.sequence(F.lit(1), F.col(count)))).select(*docs.columns)


def write_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return tokenfiles.read(*tokenfiles.write(docs, tokenizer_path()))


STAGES = [
    ("toxicity", drop_toxic),
    ("n-gram Jaccard join", drop_near_copies),
    ("benchmark decontamination", drop_contaminated),
    ("mixing sources to target weights", mix_sources),
    ("token-ID / binary output", write_tokens),
]
#: No SQL: a fitted classifier and a trained tokenizer are among the stages. tests/llm compares run() with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        to = f"{new_folder(spark, 'stage')}-{k}"
        stage(spark, docs, sf_dir).write.parquet(to)
        docs = spark.read.parquet(to)
    return docs
