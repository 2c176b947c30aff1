"""Sketches of streams: per window and set the least value of each bin, which merges in any order.

Only unfilled bins are state, because a filling is not mergeable: it is made from the postings.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor
from pyspark.sql.types import LongType, StructField, StructType

from rotahash.operators.permutations import hashed
from rotahash.params import SketchParams
from rotahash.sources.tables import token_id


def read_events(spark: SparkSession, folder: str, schema, per_trigger: int = 1) -> DataFrame:
    """Files of events as a stream; ``ts`` becomes a TIMESTAMP, which a watermark needs."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def placed(events: DataFrame, p: SketchParams) -> DataFrame:
    """Events with bin and position of their element (type, hour); the split is computed, so no table is joined."""
    elem = token_id(F.concat_ws(":", "event_type", F.hour("ts").cast("string")), 40)
    rows = events.withColumn("seed", F.lit(p.seeds[0])).withColumn("q", hashed(F.pmod(elem, F.lit(p.D)), p.split, p, p.D, p.split))
    return rows.withColumn("bin", F.floor(F.col("q") / p.d))


def bin_minima(events: DataFrame, p: SketchParams, window: Column | None = None, delay: str = "1 hour") -> DataFrame:
    """(start, user_id, bin, v) of a stream or a table alike."""
    rows = placed(events, p)
    if rows.isStreaming:
        rows = rows.withWatermark("ts", delay)
    keys = [F.col("user_id"), F.col("bin")]
    if window is not None:
        out = rows.groupBy(window.alias("w"), *keys).agg(F.min("q").alias("v"))
        return out.select(F.col("w.start").alias("start"), "user_id", "bin", "v")
    return rows.groupBy(*keys).agg(F.min("q").alias("v"))


def counted(events: DataFrame, window: Column, delay: str = "1 hour") -> DataFrame:
    """(start, stop, event_type, n) of a stream or a table alike."""
    rows = events.withWatermark("ts", delay) if events.isStreaming else events
    out = rows.groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "event_type", "n")


#: A batch pays for every partition of the state, and in complete mode for the whole result, so a stream takes its files in about so many batches.
BATCHES = 8


def in_order(spark: SparkSession, folder: str) -> int:
    """Gives the files of a folder times in the order of their names: the order in which a stream reads them. Returns how many make a batch."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    files = path.getFileSystem(spark._jsc.hadoopConfiguration())
    parts = sorted((f.getPath() for f in files.listStatus(path) if f.getPath().getName().startswith("part-")), key=lambda f: f.getName())
    for k, part in enumerate(parts):
        files.setTimes(part, 1_700_000_000_000 + 1000 * k, -1)
    return max(1, -(-len(parts) // BATCHES))


#: Every batch loads and commits each partition of the state, empty or not, so a partition is for so many rows of the stream.
STATE_ROWS = 1 << 18


def state_partitions(spark: SparkSession, rows: int) -> int:
    """As many as the rows need and all cores can work on, at most those of the session."""
    return min(int(spark.conf.get("spark.sql.shuffle.partitions")), max(spark.sparkContext.defaultParallelism, -(-rows // STATE_ROWS)))


def run_to_end(stream: DataFrame, name: str, mode: str, checkpoint: str, partitions: int | None = None) -> DataFrame:
    """All that the files hold now, as Parquet beside the checkpoint: a folder for each batch, so that a repeated one replaces itself.

    In complete mode a batch holds the whole result, so the last one is read; nothing is gathered on the driver.
    ``partitions``: of the state, those of the session by default.
    """
    out, spark = f"{checkpoint}-{name}", stream.sparkSession

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch_={number}")

    key = "spark.sql.shuffle.partitions"
    before = spark.conf.get(key)
    spark.conf.set(key, partitions or before)  # a stream keeps the setting that it starts with
    try:
        query = stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    finally:
        spark.conf.set(key, before)
    query.awaitTermination()
    done = query.lastProgress
    if done is None:
        return spark.createDataFrame([], stream.schema)
    rows = spark.read.schema(StructType([*stream.schema.fields, StructField("batch_", LongType())])).parquet(out)
    if mode == "complete":
        rows = rows.where(F.col("batch_") == rows.agg(F.max("batch_")).first()[0])
    return rows.drop("batch_")


def merge_into(path: str) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: folds a batch of bin minima into a Parquet table, a folder per batch and one that names the last whole one."""

    def merge(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        keys = [c for c in batch.columns if c != "v"]
        if number:
            batch = batch.unionByName(spark.read.parquet(f"{path}/{number - 1}"))
        batch.groupBy(*keys).agg(F.min("v").alias("v")).write.mode("overwrite").parquet(f"{path}/{number}")

    return merge


#: A call of the processor costs far more than a row of its group, so users share a call: so many groups, whatever the number of users.
GROUPS = 1024


class BinState(StatefulProcessor):
    """Of each user of a group the least value of each bin, as a map from users in state; returns what changed."""

    def init(self, handle) -> None:
        self.minima = handle.getMapState("minima", "user_id long, nobody boolean", "bins array<long>, v array<long>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        for part in rows:
            least: dict[tuple, dict[int, int]] = {}
            for user, nobody, b, q in zip(*(part[c].tolist() for c in ("user_id", "nobody", "bin", "q"))):
                mine = least.setdefault((user, nobody), {})
                mine[b] = min(q, mine.get(b, q))
            changed = []
            for user, mine in least.items():
                old = self.minima.getValue(user)
                held = dict(zip(*old)) if old else {}
                less = {b: v for b, v in mine.items() if b not in held or v < held[b]}
                if less:
                    held |= less
                    self.minima.updateValue(user, (list(held), list(held.values())))
                    changed += [(None if user[1] else user[0], b, v) for b, v in less.items()]
            yield pd.DataFrame(changed, columns=["user_id", "bin", "v"], dtype="Int64")

    def close(self) -> None:
        pass


def stateful(events: DataFrame, p: SketchParams, groups: int = GROUPS) -> DataFrame:
    """The stream of changed bins per user, from arbitrary state (needs the RocksDB state store). ``groups``: of users, at least the state's partitions."""
    user = F.col("user_id")
    rows = placed(events, p).select(F.pmod(F.hash(user), F.lit(groups)).alias("part"), F.coalesce(user, F.lit(0)).alias("user_id"), user.isNull().alias("nobody"), "bin", "q")
    return rows.groupBy("part").transformWithStateInPandas(statefulProcessor=BinState(), outputStructType="user_id long, bin long, v long", outputMode="Update", timeMode="None")
