"""Exact similarity, estimates from sketches, and their errors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rotahash.params import SketchParams


#: Added before rounding, so that sums in another order don't fall on the other side of a half.
NUDGE = 1e-10


def exact_jaccard(postings: DataFrame, pairs: DataFrame) -> DataFrame:
    """pairs (id1, id2) with inter, uni and j."""
    a = postings.select(F.col("set_id").alias("id1"), "elem")
    b = postings.select(F.col("set_id").alias("id2"), "elem")
    common = pairs.join(a, "id1").join(b, ["id2", "elem"]).groupBy("id1", "id2").agg(F.count("*").alias("inter"))
    return _with_sizes(pairs.join(common, ["id1", "id2"], "left").fillna(0, ["inter"]), postings)


def exact_all_pairs(postings: DataFrame, min_overlap: int = 1) -> DataFrame:
    """All pairs id1 < id2 that share an element: the inverted index joined to itself."""
    a = postings.select(F.col("set_id").alias("id1"), "elem")
    b = postings.select(F.col("set_id").alias("id2"), "elem")
    common = a.join(b, "elem").where("id1 < id2").groupBy("id1", "id2").agg(F.count("*").alias("inter")).where(F.col("inter") >= min_overlap)
    return _with_sizes(common, postings)


def _with_sizes(common: DataFrame, postings: DataFrame) -> DataFrame:
    sizes = postings.groupBy("set_id").agg(F.count("*").alias("n"))
    out = common.join(sizes.select(F.col("set_id").alias("id1"), F.col("n").alias("n1")), "id1").join(sizes.select(F.col("set_id").alias("id2"), F.col("n").alias("n2")), "id2")
    uni = F.col("n1") + F.col("n2") - F.col("inter")
    return out.select("id1", "id2", "inter", uni.alias("uni"), ratio(F.col("inter"), uni).alias("j"))


def ratio(a: Column, b: Column, digits: int = 6) -> Column:
    """a/b rounded half up; the rounding of the exact quotient, so engines agree."""
    scale = 10**digits
    return F.when(b == 0, None).otherwise(F.floor((a * F.lit(2 * scale) + b) / (b * F.lit(2))) / F.lit(float(scale)))


def estimate_pairs(sig: DataFrame, pairs: DataFrame, slots: int | None = None) -> DataFrame:
    """Share of equal slots: (seed, id1, id2, hits, m, j_hat). ``slots``: use the first so many only."""
    s = sig if slots is None else sig.where(F.col("slot") < slots)
    a = s.select("seed", F.col("set_id").alias("id1"), "slot", F.col("h").alias("h1"))
    b = s.select("seed", F.col("set_id").alias("id2"), "slot", F.col("h").alias("h2"))
    rows = pairs.select("id1", "id2").join(a, "id1").join(b, ["seed", "id2", "slot"])
    out = rows.groupBy("seed", "id1", "id2").agg(F.sum((F.col("h1") == F.col("h2")).cast("long")).alias("hits"), F.count("*").alias("m"))
    out = out.withColumn("hits", F.coalesce("hits", F.lit(0)))
    return out.withColumn("j_hat", ratio(F.col("hits"), F.col("m")))


def estimate_unfilled(sig: DataFrame, pairs: DataFrame) -> DataFrame:
    """Equal slots over the slots that are not empty in both; two empties are no match."""
    a = sig.select("seed", F.col("set_id").alias("id1"), "slot", F.col("h").alias("h1"))
    b = sig.select("seed", F.col("set_id").alias("id2"), "slot", F.col("h").alias("h2"))
    rows = pairs.select("id1", "id2").join(a, "id1").join(b, ["seed", "id2", "slot"])
    out = rows.groupBy("seed", "id1", "id2").agg(F.coalesce(F.sum((F.col("h1") == F.col("h2")).cast("long")), F.lit(0)).alias("hits"), F.sum((F.col("h1").isNotNull() | F.col("h2").isNotNull()).cast("long")).alias("m"))
    return out.withColumn("j_hat", ratio(F.col("hits"), F.col("m")))


def estimate_firstk(sig: DataFrame, pairs: DataFrame, k: int) -> DataFrame:
    """Of the k least positions of the union, the share that both sets hold."""
    packed = sig.groupBy("seed", "set_id").agg(F.array_sort(F.collect_list("h")).alias("s"))  # at most k entries
    a = packed.select("seed", F.col("set_id").alias("id1"), F.col("s").alias("s1"))
    b = packed.select("seed", F.col("set_id").alias("id2"), F.col("s").alias("s2"))
    rows = pairs.select("id1", "id2").join(a, "id1").join(b, ["seed", "id2"])
    least = F.slice(F.array_sort(F.array_union("s1", "s2")), 1, k)
    both = F.size(F.array_intersect(F.array_intersect(least, F.col("s1")), F.col("s2")))
    out = rows.select("seed", "id1", "id2", both.cast("long").alias("hits"), F.size(least).cast("long").alias("m"))
    return out.withColumn("j_hat", ratio(F.col("hits"), F.col("m")))


def mle_two_way(sig: DataFrame, pairs: DataFrame, sizes: DataFrame, p: SketchParams) -> DataFrame:
    """Intersection of two sets from first-k sketches by the margin-constrained likelihood.

    Both sketches are cut at the lesser of their largest positions, which makes the positions up to there a
    random sample of the universe. With x sample elements in both, y in the first only, z in the second
    only and u in neither, the likelihood x log a + y log(f1-a) + z log(f2-a) + u log(D-f1-f2+a) has one
    maximum between its bounds; it is found by bisection of the derivative as Column arithmetic.
    """
    packed = sig.groupBy("seed", "set_id").agg(F.array_sort(F.collect_list("h")).alias("s"))
    a = packed.join(sizes.select("set_id", F.col("n").alias("f1")), "set_id").select("seed", F.col("set_id").alias("id1"), F.col("s").alias("s1"), "f1")
    b = packed.join(sizes.select("set_id", F.col("n").alias("f2")), "set_id").select("seed", F.col("set_id").alias("id2"), F.col("s").alias("s2"), "f2")
    rows = pairs.select("id1", "id2").join(a, "id1").join(b, ["seed", "id2"])
    # a set smaller than k is known whole: its sketch reaches to the end of the universe
    reach = [F.when(F.size(s) < p.K, F.lit(p.D - 1)).otherwise(F.array_max(s)) for s in ("s1", "s2")]
    rows = rows.withColumn("top", F.least(*reach))
    rows = rows.withColumn("c1", F.filter("s1", lambda q: q <= F.col("top"))).withColumn("c2", F.filter("s2", lambda q: q <= F.col("top")))
    rows = rows.withColumn("x", F.size(F.array_intersect("c1", "c2"))).withColumn("y", F.size("c1") - F.col("x")).withColumn("z", F.size("c2") - F.col("x"))
    rows = rows.withColumn("u", F.col("top") + 1 - F.col("x") - F.col("y") - F.col("z"))
    low = F.greatest(F.lit(0.0), (F.col("f1") + F.col("f2") - p.D).cast("double"))
    high = F.least("f1", "f2").cast("double")
    rest = F.lit(p.D) - F.col("f1") - F.col("f2")

    def slope(t: Column) -> Column:
        def term(n, d):
            return F.when(F.col(n) == 0, 0.0).otherwise(F.col(n) / d)

        return term("x", t) - term("y", F.col("f1") - t) - term("z", F.col("f2") - t) + term("u", rest + t)

    bounds = F.struct(low.alias("lo"), high.alias("hi"))

    def halve(acc: Column, _: Column) -> Column:
        mid = (acc["lo"] + acc["hi"]) / 2
        up = slope(mid) > 0
        return F.struct(F.when(up, mid).otherwise(acc["lo"]).alias("lo"), F.when(up, acc["hi"]).otherwise(mid).alias("hi"))

    solved = F.when((F.col("x") + F.col("y") + F.col("z")) == 0, low).otherwise(F.aggregate(F.sequence(F.lit(1), F.lit(60)), bounds, halve, lambda acc: (acc["lo"] + acc["hi"]) / 2))
    out = rows.withColumn("a_hat", F.round(solved, 4))
    return out.select("seed", "id1", "id2", F.col("x").cast("long").alias("x"), F.col("y").cast("long").alias("y"), F.col("z").cast("long").alias("z"), "a_hat", F.round(solved / (F.col("f1") + F.col("f2") - solved), 6).alias("j_hat"))


def estimate_multiway(sig: DataFrame, groups: DataFrame, slots: int) -> DataFrame:
    """groups (group_id, set_id): share of slots in which all sets of a group agree."""
    rows = groups.join(sig, "set_id").groupBy("seed", "group_id", "slot").agg(F.count_distinct("h").alias("kinds"), F.count("h").alias("n"))
    need = groups.groupBy("group_id").agg(F.count("*").alias("need"))
    out = rows.join(need, "group_id").groupBy("seed", "group_id").agg(F.sum(((F.col("kinds") == 1) & (F.col("n") == F.col("need"))).cast("long")).alias("hits"))
    return out.withColumn("j_hat", ratio(F.col("hits"), F.lit(slots)))


def error_profile(est: DataFrame, exact: DataFrame, by: tuple[str, ...] = ("id1", "id2")) -> DataFrame:
    """Mean squared error, bias and population variance over the replicates (seeds)."""
    rows = est.join(exact.select("id1", "id2", "j"), ["id1", "id2"])
    out = rows.groupBy(*by).agg(F.count("*").alias("n"), F.first("j").alias("j"), F.avg("j_hat").alias("m"), F.avg(F.pow(F.col("j_hat") - F.col("j"), 2)).alias("e"), F.var_pop("j_hat").alias("v"))
    return out.select(*by, "n", "j", *(F.round(c + NUDGE, 6).alias(n) for c, n in ((F.col("e"), "mse"), (F.col("m") - F.col("j"), "bias"), (F.col("v"), "variance"))))
