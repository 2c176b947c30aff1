"""Mixing sources to target weights by weighted fair queueing.

Every source is a queue of its documents in a seeded shuffle, repeated up to ``max_epochs`` times. A
copy of a document finishes at the virtual time (tokens of its queue up to and with it) / (target of
its source). All copies are ordered by that time over the whole corpus and the order is cut where the
total budget is spent. With targets that sum to the budget, every source ends within a document or two
of its target.

Both running totals (inside a source, and over the cut) are two-level: totals of hash or time ranges
first, then a window inside one range, so no task holds more than a range even if one source has a
third of all rows. The driver sees one row per source and the one row at the cut.

Defined results: null text has size 0; a null source is a source of its own, the last in order; an
empty table gives an empty result; a source whose size is 0 has target 0 and nothing taken; rows with
equal doc_id are separate documents; further columns are kept.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rotahash.llm.bytesops import SPACE, lean, runs, slices
from rotahash.llm.durable import durable

WEIGHTS = (5.0, 2.0, 1.0)
RESULTS = ("source_size", "target", "taken", "finish")
ROWS_PER_RANGE, MAX_RANGES = 1_000, 1 << 16  # the tables of ranges stay small, and a range fits a task at any size


def sized(docs: DataFrame, keep: tuple[str, ...] = ("doc_id", "source")) -> DataFrame:
    """The named columns and ``size``: runs of bytes other than ASCII white space in the whole text."""
    kinds = T.StructType([docs.schema[c] for c in keep] + [T.StructField("size", T.LongType())])

    def count(batches):
        for b in batches:
            out = np.zeros(b.num_rows, np.int64)
            for lo, hi, data, at in slices(b.column("text")):
                start, _ = runs(data, at, ~SPACE)
                out[lo:hi] = np.diff(np.searchsorted(start, at))
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in keep), pa.array(out)], [*keep, "size"])

    return docs.select(*dict.fromkeys([*keep, "text"])).mapInArrow(lean(count), kinds)


def targets(sizes: list[tuple[str | None, int]], weights: tuple[float, ...] = WEIGHTS, cap: float = 3.0) -> list[tuple[str | None, int, float]]:
    """Source, size and target: shares of the total by weight, held at ``cap`` sizes, the excess shared again."""
    order = sorted(sizes, key=lambda x: (x[0] is None, x[0] or ""))
    weigh = [weights[i % len(weights)] for i in range(len(order))]
    left, open_, out = float(sum(n for _, n in order)), set(range(len(order))), [0.0] * len(order)
    while open_:
        total = sum(weigh[i] for i in open_)
        full = {i for i in open_ if left * weigh[i] / total > cap * order[i][1]}
        if not full:
            for i in open_:
                out[i] = left * weigh[i] / total
            break
        for i in full:
            out[i] = cap * order[i][1]
        left -= sum(out[i] for i in full)
        open_ -= full
    return [(name, n, t) for (name, n), t in zip(order, out, strict=True)]


def _ranges(rows: int) -> int:
    return min(MAX_RANGES, 1 << max(0, math.ceil(math.log2(max(1, rows / ROWS_PER_RANGE)))))


def mix(rows: DataFrame, weights: tuple[float, ...] = WEIGHTS, cap: float = 3.0, seed: int = 7) -> DataFrame:
    """``rows`` (doc_id, source, size and any others) with source_size, target, taken and finish (virtual time of the first copy).

    Other columns are kept, unless they are named as one of these.
    """
    spark, epochs = rows.sparkSession, math.ceil(cap)
    others = [c for c in rows.columns if c.lower() not in ("doc_id", "source", "size", *RESULTS)]
    rest = F.struct(*others) if others else F.lit(None).cast("struct<_: int>")
    rows = durable(rows.select("doc_id", "source", "size", rest.alias("_rest"), F.xxhash64(F.lit(seed), "doc_id").alias("_h")))
    total = rows.groupBy("source").agg(F.sum("size").alias("n"), F.count("*").alias("k")).collect()
    plan = targets([(r["source"], r["n"]) for r in total], weights, cap)
    budget, count = sum(n for _, n, _ in plan), sum(r["k"] for r in total)
    kinds = T.StructType([T.StructField("_source", T.StringType()), T.StructField("source_size", T.LongType()), T.StructField("target", T.DoubleType())])
    by_source = spark.createDataFrame(plan, kinds)
    ranges = _ranges(count)
    rows = rows.withColumn("_range", F.floor((F.col("_h").cast("double") + 2.0**63) * (ranges / 2.0**64)))
    key = Window.partitionBy("source", "_range")
    before = rows.groupBy("source", "_range").agg(F.sum("size").alias("n")).withColumn("_before", F.sum("n").over(Window.partitionBy("source").orderBy("_range")) - F.col("n"))
    before = before.select(F.col("source").alias("_s"), F.col("_range").alias("_r"), "_before")
    queued = rows.join(before, F.col("source").eqNullSafe(F.col("_s")) & (F.col("_range") == F.col("_r"))).drop("_s", "_r")
    queued = queued.withColumn("_upto", F.col("_before") + F.sum("size").over(key.orderBy("_h", "doc_id", "size")))
    queued = queued.join(F.broadcast(by_source), F.col("source").eqNullSafe(F.col("_source"))).drop("_source")
    queued = durable(queued.drop("_before", "_range"))

    def finish(epoch) -> Column:
        return F.when(F.col("target") > 0, (F.col("_upto") + F.col("source_size") * epoch) / F.col("target"))

    copies = queued.select("source", "_h", "doc_id", "size", F.explode(F.sequence(F.lit(0), F.lit(epochs - 1))).alias("_e"), "_upto", "source_size", "target").where("size > 0")
    copies = copies.withColumn("_t", finish(F.col("_e"))).select("_t", "_h", "doc_id", "_e", "size", F.least(F.floor(F.col("_t") * ranges), F.lit(8 * ranges)).alias("_slot"))
    slots = copies.groupBy("_slot").agg(F.sum("size").alias("n"))
    slots = slots.withColumn("upto", F.sum("n").over(Window.orderBy("_slot"))).where(F.col("upto") > budget).orderBy("_slot").limit(1).collect()
    taken = F.lit(epochs).cast("long")
    if slots:  # the range in which the budget runs out; the order inside it gives the cut
        spent = slots[0]["upto"] - slots[0]["n"]
        inside = copies.where(F.col("_slot") == slots[0]["_slot"]).withColumn("upto", F.sum("size").over(Window.orderBy("_t", "_h", "doc_id", "_e").rowsBetween(Window.unboundedPreceding, 0)) + spent)
        cut = inside.where(F.col("upto") > budget).orderBy("_t", "_h", "doc_id", "_e").limit(1).collect()[0]
        own = F.struct(F.col("_h"), F.col("doc_id"))
        taken = F.lit(0).cast("long")
        for e in range(epochs):
            at = finish(F.lit(e))
            tie = (own < F.struct(F.lit(cut["_h"]).cast("long"), F.lit(cut["doc_id"]).cast("long"))) | ((F.col("_h") == cut["_h"]) & F.col("doc_id").eqNullSafe(F.lit(cut["doc_id"])) & (F.lit(e) < cut["_e"]))
            taken = taken + F.when((at < cut["_t"]) | ((at == cut["_t"]) & tie), 1).otherwise(0)
    return queued.withColumn("finish", finish(F.lit(0))).withColumn("taken", F.when(F.col("target") > 0, F.col("size") * taken).otherwise(0).cast("long")).select("doc_id", "source", "size", *RESULTS, *([F.col("_rest")[c].alias(c) for c in others]))
