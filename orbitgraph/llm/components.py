"""Connected components of a link table, distributed: least labels with pointer jumping, materialised each round."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialise


def components(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """links: a, b (long). Returns v, label: every vertex of a link with the least vertex of its component.

    Each round takes the least label among the neighbours (an aggregate, combined within tasks) and then the label of
    the label, so the rounds grow with the logarithm of the longest chain. Only counts come to the driver."""
    both = links.where(F.col("a") != F.col("b"))
    edges = materialise(both.select(F.col("a").alias("v"), F.col("b").alias("w")).unionAll(both.select(F.col("b"), F.col("a"))).distinct(), "edges")
    labels = materialise(edges.groupBy("v").agg(F.least(F.col("v"), F.min("w")).alias("label")), "labels")
    before = labels
    for _ in range(max_rounds):
        near = edges.join(labels.select(F.col("v").alias("w"), F.col("label").alias("of_w")), "w").groupBy("v").agg(F.min("of_w").alias("low"))
        lower = labels.join(near, "v", "left").select("v", F.col("label").alias("old"), F.least("label", "low").alias("label"))
        jumped = lower.join(labels.select(F.col("v").alias("label"), F.col("label").alias("next")), "label", "left")
        new = materialise(jumped.select("v", "old", F.coalesce(F.least("label", "next"), "label").alias("label")), "labels")
        discard(before)
        labels, before = new.select("v", "label"), new
        if new.where(F.col("old") != F.col("label")).limit(1).count() == 0:
            discard(edges)
            return labels
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
