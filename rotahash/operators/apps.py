"""Uses of the sketches: candidate search, joins, clusters, deduplication, votes, and upkeep of signatures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rotahash.operators import estimates as E
from rotahash.operators.components import components


def band_keys(sig: DataFrame, rows: int) -> DataFrame:
    """(seed, set_id, band, key): md5 of each run of ``rows`` slots."""
    parts = sig.groupBy("seed", "set_id", F.floor(F.col("slot") / rows).cast("int").alias("band")).agg(F.array_sort(F.collect_list(F.struct("slot", "h"))).alias("s"))
    return parts.select("seed", "set_id", "band", F.md5(F.array_join(F.col("s.h").cast("array<string>"), ",")).alias("key"))


def candidate_pairs(bands: DataFrame, max_bucket: int | None = None) -> DataFrame:
    """(id1, id2), id1 < id2, that share a band. A bucket of more than ``max_bucket`` sets links each set to its least id instead of to all, so its size stays linear and it stays connected."""
    a = bands.select("seed", "band", "key", F.col("set_id").alias("id1"))
    b = bands.select("seed", "band", "key", F.col("set_id").alias("id2"))
    on = ["seed", "band", "key"]
    if max_bucket is None:
        return a.join(b, on).where("id1 < id2").select("id1", "id2").distinct()
    size = bands.groupBy(*on).agg(F.count("*").alias("n"), F.min("set_id").alias("least"))
    small = size.where(F.col("n").between(2, max_bucket)).select(*on)
    pairs = a.join(small, on).join(b, on).where("id1 < id2").select("id1", "id2")
    star = b.join(size.where(F.col("n") > max_bucket), on).where("least < id2").select(F.col("least").alias("id1"), "id2")
    return pairs.unionByName(star).distinct()


def verify_pairs(candidates: DataFrame, postings: DataFrame, tau: Column | float) -> DataFrame:
    """The candidates whose exact similarity is at least tau; only their sets are read."""
    ids = candidates.select(F.col("id1").alias("set_id")).union(candidates.select("id2")).distinct()
    own = postings.join(ids, "set_id", "left_semi")
    tau = F.lit(tau) if not isinstance(tau, Column) else tau
    return E.exact_jaccard(own, candidates).where(F.col("inter") >= tau * F.col("uni"))


def recall(j: float, bands: int, rows: int) -> float:
    """Probability that a pair of similarity j shares a band."""
    return 1 - (1 - j**rows) ** bands


def jaccard_join(postings: DataFrame, tau: float) -> DataFrame:
    """All pairs of similarity at least tau, exact: rare-token prefixes meet, sizes are compared, then sets."""
    df = postings.groupBy("elem").agg(F.count("*").alias("df"))
    sized = postings.join(df, "elem").withColumn("n", F.count("*").over(Window.partitionBy("set_id")))
    ranked = sized.withColumn("r", F.row_number().over(Window.partitionBy("set_id").orderBy("df", "elem")))
    # two such sets share an element among the first n - ceil(tau n) + 1 of either
    prefix = ranked.where(F.col("r") <= F.col("n") - F.ceil(F.lit(tau) * F.col("n") - 1e-9) + 1)
    a = prefix.select("elem", F.col("set_id").alias("id1"), F.col("n").alias("n1"))
    b = prefix.select("elem", F.col("set_id").alias("id2"), F.col("n").alias("n2"))
    meet = a.join(b, "elem").where((F.col("id1") < F.col("id2")) & (F.col("n1") >= F.lit(tau) * F.col("n2")) & (F.col("n2") >= F.lit(tau) * F.col("n1")))
    return verify_pairs(meet.select("id1", "id2").distinct(), postings, tau)


def clusters(pairs: DataFrame) -> DataFrame:
    """(id, component) of the linked sets."""
    return components(pairs.select(F.col("id1").alias("a"), F.col("id2").alias("b")))


def dedup(rows: DataFrame, id_column: str, groups: DataFrame) -> DataFrame:
    """rows without those whose group has a smaller id."""
    gone = groups.where("id <> component").select(F.col("id").alias("_gone"))
    return rows.join(gone, F.col(id_column) == F.col("_gone"), "left_anti")


def topk_similar(queries: DataFrame, sig: DataFrame, k: int) -> DataFrame:
    """(seed, id1, id2, hits): for each query signature the k sets that agree in most slots, ties by id."""
    q = queries.select("seed", "slot", F.col("set_id").alias("id1"), "h")
    s = sig.select("seed", "slot", F.col("set_id").alias("id2"), "h")
    hits = q.join(s, ["seed", "slot", "h"]).where("id1 <> id2").groupBy("seed", "id1", "id2").agg(F.count("*").alias("hits"))
    order = Window.partitionBy("seed", "id1").orderBy(F.desc("hits"), "id2")
    return hits.withColumn("r", F.row_number().over(order)).where(F.col("r") <= k)


def knn_vote(neighbours: DataFrame, labels: DataFrame) -> DataFrame:
    """(id1, votes, positive, vote): the majority of 0/1 labels (id, label) among the neighbours; a tie is 0."""
    rows = neighbours.join(labels, F.col("id2") == F.col("id"))
    out = rows.groupBy("id1").agg(F.count("*").alias("votes"), F.sum("label").cast("long").alias("positive"))
    return out.withColumn("vote", (F.col("positive") * 2 > F.col("votes")).cast("int"))


def sig_features(sig: DataFrame, size: int) -> DataFrame:
    """(seed, set_id, features): indices of a sparse one-hot vector of the pairs (slot, h), hashed into ``size``."""
    index = F.pmod(F.xxhash64("slot", "h"), F.lit(size)).cast("int")
    return sig.where("h is not null").groupBy("seed", "set_id").agg(F.sort_array(F.collect_set(index)).alias("features"))


def bin_minima(base: DataFrame) -> DataFrame:
    """(seed, set_id, bin, v): the mergeable state of a binned sketch; fillings are made from it and never merged."""
    return base.groupBy("seed", "set_id", "bin").agg(F.min("q").alias("v"))


def merge_minima(*states: DataFrame) -> DataFrame:
    """The state of the unions of sets: least value per bin."""
    out = states[0]
    for s in states[1:]:
        out = out.unionByName(s)
    return out.groupBy("seed", "set_id", "bin").agg(F.min("v").alias("v"))


def pair_quality(truth: DataFrame, found: DataFrame) -> DataFrame:
    """One row: true pairs, found pairs, both, recall and precision."""
    t = truth.select("id1", "id2", F.lit(1).alias("t"))
    f = found.select("id1", "id2", F.lit(1).alias("f"))
    rows = t.join(f, ["id1", "id2"], "full")
    out = rows.agg(F.count("t").alias("true_pairs"), F.count("f").alias("found_pairs"), F.count(F.when(F.col("t").isNotNull() & F.col("f").isNotNull(), 1)).alias("both"))
    return out.select("*", E.ratio(F.col("both"), F.col("true_pairs")).alias("recall"), E.ratio(F.col("both"), F.col("found_pairs")).alias("precision"))
