"""Permutations as tables, and the choice of how to look them up."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rotahash.functions import hashes
from rotahash.params import BROADCAST_ROWS, SketchParams, digest


def seed_table(spark: SparkSession, seeds: tuple[int, ...]) -> DataFrame:
    return spark.createDataFrame([(s,) for s in seeds], "seed int")


#: Beyond so many positions a permutation is ranked inside ranges of its sort key, so no task sorts it whole.
RANKED_IN_ONE = 1 << 16


def permutation(spark: SparkSession, tag: str, n: int, seeds: tuple[int, ...]) -> DataFrame:
    """(seed, pos, rank): positions 0..n-1 in the order of md5('seed:tag:pos'); rank is the place in that order."""
    rows = spark.range(n).select(F.col("id").alias("pos")).crossJoin(F.broadcast(seed_table(spark, seeds)))
    rows = rows.withColumn("key", hashes.md5_key(F.col("seed"), tag, F.col("pos")))
    if n <= RANKED_IN_ONE:
        order = Window.partitionBy("seed").orderBy("key", "pos")
        return rows.select("seed", "pos", (F.row_number().over(order) - 1).cast("long").alias("rank"))
    digits = 2 if n <= 1 << 22 else 4
    rows = rows.withColumn("part", F.substring("key", 1, digits))
    before = rows.groupBy("seed", "part").agg(F.count("*").alias("k"))  # at most 16^digits rows a seed
    before = before.select("seed", "part", (F.sum("k").over(Window.partitionBy("seed").orderBy("part")) - F.col("k")).alias("base"))
    order = Window.partitionBy("seed", "part").orderBy("key", "pos")
    ranked = rows.withColumn("own", F.row_number().over(order) - 1)
    return ranked.join(F.broadcast(before), ["seed", "part"]).select("seed", "pos", (F.col("base") + F.col("own")).cast("long").alias("rank"))


def slot_permutations(spark: SparkSession, tag: str, slots: int, n: int, seeds: tuple[int, ...]) -> DataFrame:
    """(seed, slot, pos, rank): one independent permutation per slot, in the order of md5('seed:tag+slot:pos')."""
    rows = spark.range(n * slots).select(F.floor(F.col("id") / n).cast("int").alias("slot"), (F.col("id") % n).alias("pos")).crossJoin(F.broadcast(seed_table(spark, seeds)))
    order = Window.partitionBy("seed", "slot").orderBy(hashes.md5_key(F.col("seed"), F.concat(F.lit(tag), F.col("slot")), F.col("pos")), "pos")
    return rows.withColumn("rank", (F.row_number().over(order) - 1).cast("long"))


def lookup(rows: DataFrame, table: DataFrame, size: int, on: list[str]) -> DataFrame:
    """rows joined to a table of known size: broadcast up to BROADCAST_ROWS, dealt out by the key beyond."""
    return rows.join(F.broadcast(table) if size <= BROADCAST_ROWS else table, on)


def per_seed(p: SketchParams, of) -> Column:
    """A Column that depends on the seed: of(seed) for each of the few seeds."""
    out = None
    for seed in p.seeds:
        out = of(seed) if out is None else F.when(F.col("seed") == seed, of(seed)).otherwise(out)
    return out


def mix_constants(seed: int, bits: int, rounds: int = 3) -> list[tuple[int, int]]:
    return [(digest(seed, "mix", r, "a") % (1 << bits) | 1, digest(seed, "mix", r, "c") % (1 << bits)) for r in range(rounds)]


def feistel_keys(seed: int, rounds: int = 4) -> list[int]:
    return [digest(seed, "feistel", r) % (1 << 60) for r in range(rounds)]


def hashed(x: Column, kind: str, p: SketchParams, size: int, tag: str) -> Column:
    """x in [0, size) under the hash function ``kind`` of the row's seed."""
    if kind == "2u":
        q = p.linear(0, tag, size)[2]
        return hashes.two_universal(x, per_seed(p, lambda s: F.lit(p.linear(s, tag, size)[0])), per_seed(p, lambda s: F.lit(p.linear(s, tag, size)[1])), q, size)
    if kind == "4u":
        q = p.cubic(0, tag, size)[4]
        return hashes.four_universal(x, [per_seed(p, lambda s, i=i: F.lit(p.cubic(s, tag, size)[i])) for i in range(4)], q, size)
    if kind == "murmur":
        return hashes.murmur(x, F.col("seed"), size)
    if kind == "mix":
        bits = size.bit_length() - 1
        return per_seed(p, lambda s: hashes.mix_bijection(x, mix_constants(s, bits), bits))
    if kind == "feistel":
        return per_seed(p, lambda s: hashes.feistel_walk(x, feistel_keys(s), size))
    if kind == "identity":
        return x
    raise ValueError(f"no such hash function: {kind}")


def positions(postings: DataFrame, p: SketchParams) -> DataFrame:
    """postings (set_id, elem) with seed and the shuffled position q of the element."""
    spark = postings.sparkSession
    rows = postings.select("set_id", "elem").crossJoin(F.broadcast(seed_table(spark, p.seeds)))
    if p.split == "perm":
        table = permutation(spark, "sigma", p.D, p.seeds).select("seed", F.col("pos").alias("elem"), F.col("rank").alias("q"))
        return lookup(rows, table, p.D * len(p.seeds), ["seed", "elem"])
    return rows.withColumn("q", hashed(F.col("elem"), p.split, p, p.D, p.split))
