"""Streams equal batches on the same rows, late rows are dropped, and merged tables equal one pass."""

import os

import pandas as pd
import pytest
from pyspark.sql import functions as F

from rotahash.plans.operator_queries import STREAM_P
from rotahash.sources.tables import load_table
from rotahash.streaming import bins


def test_stream_equals_batch(spark, tiny, tmp_path):
    rows = load_table(spark, tiny, "events")
    rows.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = bins.bin_minima(bins.read_events(spark, str(tmp_path / "in"), rows.schema), STREAM_P)
    got = bins.run_to_end(stream, "stream_minima", "complete", str(tmp_path / "state"))
    batch = bins.bin_minima(rows.withColumn("ts", F.col("ts").cast("timestamp")), STREAM_P)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, batch.collect()))


def test_late_rows_are_dropped(spark, tmp_path):
    kinds = "event_id long, ts timestamp_ntz, user_id long, event_type string"
    import datetime as dt

    at = dt.datetime(2024, 1, 1)
    for k, hours in enumerate((0, 10, 11, 1, 20)):  # the fourth file is behind the watermark of the batch before
        spark.createDataFrame([(k, at + dt.timedelta(hours=hours), 1, "view")], kinds).coalesce(1).write.parquet(str(tmp_path / f"w{k}"))
        (tmp_path / "in").mkdir(exist_ok=True)
        (part,) = (tmp_path / f"w{k}").glob("part-*.parquet")
        to = tmp_path / "in" / f"part-{k}.parquet"
        part.rename(to)
        os.utime(to, (1_700_000_000 + 100 * k,) * 2)  # files are read in the order of their times
    schema = spark.read.parquet(str(tmp_path / "in")).schema
    stream = bins.counted(bins.read_events(spark, str(tmp_path / "in"), schema), F.window("ts", "1 hour"))
    got = bins.run_to_end(stream, "stream_late_rows", "append", str(tmp_path / "state"))
    assert got.where("hour(start) = 1").count() == 0


def test_foreach_batch_merge(spark, tmp_path):
    fold = bins.merge_into(str(tmp_path / "sink"))
    a = spark.createDataFrame([(1, 0, 9), (1, 1, 4)], "user_id long, bin long, v long")
    b = spark.createDataFrame([(1, 0, 3), (2, 5, 8)], "user_id long, bin long, v long")
    for number, batch in enumerate((a, b)):
        fold(batch, number)
        fold(batch, number)  # a repeated batch changes nothing
    assert sorted(map(tuple, spark.read.parquet(str(tmp_path / "sink" / "1")).collect())) == [(1, 0, 3), (1, 1, 4), (2, 5, 8)]


def test_stateful_processor_plan(spark, tiny, tmp_path):
    rows = load_table(spark, tiny, "events")
    rows.coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = bins.stateful(bins.read_events(spark, str(tmp_path / "in"), rows.schema), STREAM_P)
    assert stream.isStreaming and stream.columns == ["user_id", "bin", "v"]
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        got = bins.run_to_end(stream, "stream_state", "update", str(tmp_path / "state"))
    except Exception as e:  # the state server needs packages that may be missing
        pytest.skip(str(e)[:200])
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    batch = bins.bin_minima(rows.withColumn("ts", F.col("ts").cast("timestamp")), STREAM_P)
    least = got.groupBy("user_id", "bin").agg(F.min("v").alias("v"))
    assert sorted(map(tuple, least.collect())) == sorted(map(tuple, batch.collect()))


def test_batches_do_not_grow_with_the_files(spark, tiny, tmp_path):
    rows = load_table(spark, tiny, "events")
    rows.repartition(30).write.parquet(str(tmp_path / "in"))
    take = bins.in_order(spark, str(tmp_path / "in"))
    stream = bins.counted(bins.read_events(spark, str(tmp_path / "in"), rows.schema, take), F.window("ts", "1 hour"))
    got = bins.run_to_end(stream, "many", "complete", str(tmp_path / "state"))
    batch = bins.counted(rows.withColumn("ts", F.col("ts").cast("timestamp")), F.window("ts", "1 hour"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, batch.collect()))
    assert 1 < len(list(tmp_path.glob("state-many/batch_=*"))) <= bins.BATCHES + 1


def test_users_share_a_call_of_the_state():
    class Held(dict):
        def getValue(self, key):
            return self.get(key)

        def updateValue(self, key, value):
            self[key] = value

    class Handle:
        def getMapState(self, *kinds):
            return held

    held, state = Held(), bins.BinState()
    state.init(Handle())

    def call(*rows):
        frames = state.handleInputRows((0,), iter([pd.DataFrame(rows, columns=["part", "user_id", "nobody", "bin", "q"])]), None)
        return sorted((tuple(None if pd.isna(x) else int(x) for x in r) for f in frames for r in f.itertuples(index=False)), key=str)

    assert call((0, 1, False, 3, 9), (0, 2, False, 3, 5), (0, 1, False, 3, 7), (0, 0, True, 4, 2)) == [(1, 3, 7), (2, 3, 5), (None, 4, 2)]
    assert call((0, 1, False, 3, 8), (0, 2, False, 3, 4), (0, 2, False, 6, 1)) == [(2, 3, 4), (2, 6, 1)]
    assert {k: dict(zip(*v)) for k, v in held.items()} == {(1, False): {3: 7}, (2, False): {3: 4, 6: 1}, (0, True): {4: 2}}


def test_state_has_the_partitions_that_its_rows_need(spark, tiny, tmp_path):
    rows = load_table(spark, tiny, "events")
    rows.coalesce(1).write.parquet(str(tmp_path / "in"))
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "40")
    try:
        wanted = bins.state_partitions(spark, rows.count())
        assert wanted == spark.sparkContext.defaultParallelism and bins.state_partitions(spark, 10 * bins.STATE_ROWS) == 10
        assert bins.state_partitions(spark, 10**9) == 40
        stream = bins.counted(bins.read_events(spark, str(tmp_path / "in"), rows.schema), F.window("ts", "1 hour"))
        got = bins.run_to_end(stream, "few", "complete", str(tmp_path / "state"), wanted)
        assert spark.conf.get("spark.sql.shuffle.partitions") == "40"
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    batch = bins.counted(rows.withColumn("ts", F.col("ts").cast("timestamp")), F.window("ts", "1 hour"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, batch.collect()))
    assert len(list((tmp_path / "state" / "state" / "0").glob("[0-9]*"))) == wanted
