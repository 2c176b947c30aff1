"""Storage that outlives executors: checkpoints and files in the folder the cluster names."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; a temporary folder only where it is unset on a local master, as in tests."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not where:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        where = getattr(spark.sparkContext, "_rotahash_dir", None) or tempfile.mkdtemp(prefix="rotahash-")
        spark.sparkContext._rotahash_dir = where
    return where


def durable(df: DataFrame, eager: bool = True) -> DataFrame:
    """The rows of df on shared storage with their lineage cut, so that a lost executor repeats nothing before it."""
    spark = df.sparkSession
    if spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        spark.sparkContext.setCheckpointDir(shared_dir(spark))
    return df.checkpoint(eager)


def new_folder(spark: SparkSession, kind: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/rotahash-{kind}-{uuid.uuid4().hex}"


def partitions(spark: SparkSession) -> int:
    """The session's shuffle width: the cluster's own measure of the input's size."""
    return max(2, int(spark.conf.get("spark.sql.shuffle.partitions")))


def free_name(df: DataFrame, stem: str) -> str:
    """A column name that df does not have."""
    taken = {c.lower() for c in df.columns}
    while stem.lower() in taken:
        stem = f"_{stem}"
    return stem
