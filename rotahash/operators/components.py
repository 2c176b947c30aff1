"""Connected components of a table of links, with nothing but aggregates and joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rotahash.plans.storage import settled


def components(links: DataFrame, max_rounds: int = 200) -> DataFrame:
    """(id, component) of every id in ``links`` (a, b); component is the least id reachable.

    Each round takes the least label among the neighbours and then the label's own label (pointer
    jumping), so long chains shrink geometrically. Rounds are cut by checkpoints, and the loop ends when no
    label changes. Empty links give an empty table; self-links and repeated links are harmless.
    """
    both = links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a is not null and b is not null").distinct()
    both = settled(both)
    labels = settled(both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("label")).select(F.col("a").alias("id"), "label"))
    for _ in range(max_rounds):
        near = both.join(labels.select(F.col("id").alias("b"), "label"), "b").groupBy("a").agg(F.min("label").alias("near"))
        step = labels.join(near, F.col("id") == F.col("a"), "left").select("id", "label", F.least("label", "near").alias("next"))
        jump = labels.select(F.col("id").alias("_root"), F.col("label").alias("_up"))
        after = settled(step.join(jump, F.col("next") == F.col("_root"), "left").select("id", "label", F.least("next", "_up").alias("next")))
        changed = after.where("next < label").limit(1).count()
        labels = after.select("id", F.col("next").alias("label"))
        if not changed:
            return labels.select("id", F.col("label").alias("component"))
    raise RuntimeError("the components did not settle")
