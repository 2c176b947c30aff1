"""Sketches of sets: standard, rotating and binned MinHash with every way to fill empty bins, and first-k.

All take postings (set_id, elem), distinct, and return (seed, set_id, slot, h); h is null in a slot that
stays empty. Work is relational: a slot reads the elements of one bin of one set, so the join key is
(set, bin) and a giant set is spread over its bins, and minima are partial before any exchange.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rotahash.functions import hashes
from rotahash.operators.permutations import hashed, lookup, permutation, positions, slot_permutations
from rotahash.params import SketchParams

SIG = ["seed", "set_id", "slot", "h"]


def slot_table(spark: SparkSession, p: SketchParams) -> DataFrame:
    """(seed, slot, bin0, turn, coin, probes): what every set's slot does; M rows a seed."""
    rows = [(seed, s, p.bin_of(s, seed), p.rotation(s), p.coin(s, seed), [p.probe(s, t, seed) for t in range(p.attempts)] if p.donor == "uniform" and p.fill != "none" else []) for seed in p.seeds for s in range(p.slots)]
    return spark.createDataFrame(rows, "seed int, slot int, bin0 long, turn long, coin int, probes array<long>")


def std_minhash(postings: DataFrame, p: SketchParams) -> DataFrame:
    """Slot s: the least rank under an independent permutation s."""
    spark = postings.sparkSession
    rows = postings.select("set_id", F.col("elem").alias("pos")).withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(p.slots - 1))))
    table = slot_permutations(spark, "std", p.slots, p.D, p.seeds)
    return lookup(rows, table, p.slots * p.D * len(p.seeds), ["slot", "pos"]).groupBy("seed", "set_id", "slot").agg(F.min("rank").alias("h"))


def rot_minhash(postings: DataFrame, p: SketchParams) -> DataFrame:
    """Slot s: the least value of one permutation turned by s+1, read at the shuffled positions."""
    spark = postings.sparkSession
    rows = positions(postings, p).withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(p.slots - 1))))
    rows = rows.withColumn("pos", F.pmod(F.col("q") - F.col("slot") - 1, F.lit(p.D)))
    if p.inner == "perm":
        table = permutation(spark, "sigma" if p.share else "pi", p.D, p.seeds)
        rows = lookup(rows, table, p.D * len(p.seeds), ["seed", "pos"])
    else:
        rows = rows.withColumn("rank", hashed(F.col("pos"), p.inner, p, p.D, f"inner-{p.inner}"))
    return rows.groupBy("seed", "set_id", "slot").agg(F.min("rank").alias("h"))


def binned(postings: DataFrame, p: SketchParams) -> DataFrame:
    """(seed, set_id, q, bin, off) of every element."""
    bin_, off = hashes.split_bins(F.col("q"), p.d)
    return positions(postings, p).select("seed", "set_id", "q", bin_.alias("bin"), off.alias("off"))


#: Beyond so many bins the occupied ones are a list instead of a bit set.
BIT_BINS = 4096
BIN = ["seed", "set_id", "bin"]


def occupied(bins: DataFrame, p: SketchParams) -> DataFrame:
    """(seed, set_id, occupied): the bins of a set that hold something, as words of 64 bits; partial before the exchange."""
    if p.K > BIT_BINS:
        return bins.groupBy("seed", "set_id").agg(F.collect_set("bin").alias("occupied"))  # at most K entries
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("bin").bitwiseAND(F.lit(63)).cast("int"))
    words = [F.coalesce(F.bit_or(F.when(F.shiftright("bin", 6) == w, bit)), F.lit(0).cast("long")) for w in range(-(-p.K // 64))]
    return bins.groupBy("seed", "set_id").agg(F.array(*words).alias("occupied"))


def donors(bins: DataFrame, p: SketchParams) -> DataFrame:
    """(seed, set_id, slot, turn, read, dist): the bin each slot of each set reads. bins: (seed, set_id, bin), repeats allowed.

    dist is 0 in the first scan, null if nothing is read, and else the number of bins to the donor (1 for a
    uniform donor). The slot table and so every probe is the same for all sets, which is what makes two sets
    agree. A slot looks at its first few probes before the others; where no probe hits an occupied bin the
    next one clockwise is the donor.
    """
    spark = bins.sparkSession
    rows = occupied(bins, p).join(F.broadcast(slot_table(spark, p)), "seed")
    k, start = F.lit(p.K).cast("long"), F.col("bin0")

    def holds(b: Column) -> Column:
        if p.K > BIT_BINS:
            return F.array_contains("occupied", b)
        return F.bit_get(F.get("occupied", F.shiftright(b, 6).cast("int")), b.bitwiseAND(F.lit(63)).cast("int")) == 1

    there = F.filter(F.sequence(F.lit(0).cast("long"), k - 1), holds)
    right = F.array_min(F.transform(there, lambda b: F.pmod(b - start, k)))
    left = F.array_min(F.transform(there, lambda b: F.pmod(start - b, k)))
    clockwise = F.pmod(start + right, k)
    distance = F.when(F.lit(p.donor == "two_way") & (F.col("coin") < 0), left).otherwise(right)
    if p.fill == "none":
        donor: Column = F.lit(None).cast("long")
    elif p.donor == "clockwise":
        donor = clockwise
    elif p.donor == "two_way":
        donor = F.when(F.col("coin") > 0, clockwise).otherwise(F.pmod(start - left, k))
    else:
        steps = [n for n in (0, 4, 16, p.attempts) if n <= p.attempts]
        hits = [F.get(F.filter(F.slice("probes", lo + 1, hi - lo), holds), F.lit(0)) for lo, hi in zip(steps, steps[1:], strict=False) if hi > lo]
        donor = F.coalesce(*hits, clockwise)
        distance = F.lit(1)
    first = holds(start)
    if p.fill == "none":
        distance = F.lit(None)
    else:  # never null, so no join asks for the donor twice
        donor = F.coalesce(donor, F.lit(-1).cast("long"))
    return rows.select("seed", "set_id", "slot", "turn", F.when(first, start).otherwise(donor).alias("read"), F.when(first, F.lit(0)).otherwise(distance).cast("long").alias("dist"))


def bin_minhash(postings: DataFrame, p: SketchParams) -> DataFrame:
    """K bins and one minimum per bin; empty slots are null (fill 'none') or copy their donor's value (fill 'copy'). The elements meet in one exchange, after partial minima."""
    minima = binned(postings, p).groupBy(*BIN).agg(F.min("q").alias("v"))
    # the condition keeps v in both uses of the minima, so that Spark shares their exchange
    reads = donors(minima.where("v is not null"), p)
    out = reads.join(minima, (reads.seed == minima.seed) & (reads.set_id == minima.set_id) & (reads["read"] == minima.bin), "left")
    h = F.col("v") + (F.col("dist") * F.lit(p.D + 1) if p.copy_offset else F.lit(0))
    return out.select(reads.seed, reads.set_id, "slot", h.cast("long").alias("h"))


def refilled(postings: DataFrame, p: SketchParams) -> DataFrame:
    """Fill 'fresh' or 'rotate': every slot hashes the offsets of the bin it reads with its own permutation, or with its turn of a single short one.

    The elements are dealt out once, by (set, bin), so a giant set is spread over its bins. The same exchange
    serves the search for donors and the reads; a slot reads one bin, so its minimum is found where the bin is.
    """
    spark = postings.sparkSession
    keys = " and ".join(f"{c} is not null" for c in BIN)
    base = binned(postings, p).select(*BIN, "off").where(keys).repartition(*BIN)
    # the minimum keeps off in this use of the exchange, so that Spark shares it
    bins = base.groupBy(*BIN).agg(F.min("off").alias("least")).where("least is not null")
    reads = donors(bins, p).withColumnRenamed("read", "bin")
    rows = reads.join(base, BIN)
    if p.fill == "rotate":
        rows = rows.withColumn("pos", F.pmod(F.col("off") - F.col("turn"), F.lit(p.d)))
        if p.inner == "feistel":
            rows = rows.withColumn("rank", hashed(F.col("pos"), "feistel", p, p.d, "pi"))
        elif p.share:  # the order of the split's first d positions serves as the short permutation
            order = Window.partitionBy("seed").orderBy("rank")
            head = permutation(spark, "sigma", p.D, p.seeds).where(F.col("pos") < p.d)
            short = head.select("seed", "pos", (F.row_number().over(order) - 1).cast("long").alias("rank"))
            rows = lookup(rows, short, p.d * len(p.seeds), ["seed", "pos"])
        else:
            rows = lookup(rows, permutation(spark, "pi", p.d, p.seeds), p.d * len(p.seeds), ["seed", "pos"])
    else:
        rows = rows.withColumn("pos", F.col("off"))
        rows = lookup(rows, slot_permutations(spark, "inner", p.slots, p.d, p.seeds), p.slots * p.d * len(p.seeds), ["seed", "slot", "pos"])
        if p.implicit:  # the split's own order is the permutation of a first read
            rows = rows.withColumn("rank", F.when((F.col("dist") == 0) & (F.col("slot") < p.K), F.col("off")).otherwise(F.col("rank")))
    return rows.groupBy(*BIN, "slot").agg(F.min(F.col("rank") + F.col("bin") * p.d).alias("h")).select(*SIG)


def sketch(postings: DataFrame, p: SketchParams) -> DataFrame:
    """Binned MinHash with the filling of p."""
    return (bin_minhash if p.fill in ("none", "copy") else refilled)(postings, p).select(*SIG)


def rotbin_minhash(postings: DataFrame, p: SketchParams) -> DataFrame:
    """Rotating binned MinHash: one short permutation of length D/K, turned by the slot number."""
    return sketch(postings, p.with_(fill="rotate"))


def hash_evaluations(postings: DataFrame, p: SketchParams, method: str) -> DataFrame:
    """(seed, set_id, n): how many ranks a method looks up for each set."""
    if method in ("std", "rot"):
        return positions(postings, p).groupBy("seed", "set_id").agg((F.count("*") * p.slots).alias("n"))
    base = binned(postings, p)
    if p.fill in ("none", "copy"):
        return base.groupBy("seed", "set_id").agg(F.count("*").alias("n"))
    sizes = base.groupBy("seed", "set_id", "bin").agg(F.count("*").alias("k"))
    reads = donors(base, p).withColumnRenamed("read", "bin")
    return reads.join(sizes, ["seed", "set_id", "bin"]).groupBy("seed", "set_id").agg(F.sum("k").alias("n"))


def firstk_sketch(postings: DataFrame, p: SketchParams, salts: int = 16) -> DataFrame:
    """The K least shuffled positions of each set; slot is their place. Each salt of a set keeps its K least first, so a giant set is not sorted by one task."""
    rows = positions(postings, p).withColumn("salt", F.pmod(F.xxhash64("elem"), F.lit(salts)))
    own = Window.partitionBy("seed", "set_id", "salt").orderBy("q")
    rows = rows.withColumn("r", F.row_number().over(own)).where(F.col("r") <= p.K)
    order = Window.partitionBy("seed", "set_id").orderBy("q")
    rows = rows.withColumn("slot", (F.row_number().over(order) - 1).cast("int")).where(F.col("slot") < p.K)
    return rows.select("seed", "set_id", "slot", F.col("q").alias("h"))


def pack(sig: DataFrame) -> DataFrame:
    """(seed, set_id, sig): the slots in order; at most M entries."""
    rows = sig.groupBy("seed", "set_id").agg(F.array_sort(F.collect_list(F.struct("slot", "h"))).alias("s"))
    return rows.select("seed", "set_id", F.col("s.h").alias("sig"))


def written(sig: DataFrame) -> DataFrame:
    """(seed, set_id, sig): the slots in order as text, empty where a slot is."""
    return pack(sig).select("seed", "set_id", F.array_join(F.transform("sig", lambda h: F.coalesce(h.cast("string"), F.lit(""))), ",").alias("sig"))


def unpack(packed: DataFrame) -> DataFrame:
    return packed.select("seed", "set_id", F.posexplode("sig").alias("slot", "h"))
