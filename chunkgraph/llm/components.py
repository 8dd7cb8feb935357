"""Connected components of an undirected graph given as links, by joins alone: smallest reachable id of each node."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import forget, settle


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """links: a, b (long). Returns node, component for every node of a link; nodes without links are not listed.

    Each round every node takes the least label among its neighbours and itself, and then its label's own label, so
    long chains shrink by more than half a round. Rounds end when no label changes. Each round is written to the
    shared folder, so a lost executor repeats one round at most. Null ends and self-links are left out.
    """
    both = links.where(F.col("a").isNotNull() & F.col("b").isNotNull() & (F.col("a") != F.col("b"))).select("a", "b")
    both = settle(both.unionAll(both.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    size = both.count()
    labels = settle(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.col("a")).alias("component")).select("node", "component"), size)
    for _ in range(most_rounds):
        near = both.join(labels.select(F.col("node").alias("b"), F.col("component").alias("seen")), "b").groupBy(F.col("a").alias("node")).agg(F.min("seen").alias("seen"))
        hooked = labels.join(near, "node", "left").select("node", F.col("component").alias("was"), F.least("component", "seen").alias("component"))
        jump = labels.select(F.col("node").alias("component"), F.col("component").alias("above"))
        stepped = settle(hooked.join(jump, "component", "left").select("node", F.least("component", F.coalesce("above", "component")).alias("component"), "was"), size)
        changed = stepped.where("component < was").limit(1).count()
        forget(labels)
        labels = stepped.select("node", "component")
        if not changed:
            forget(both)
            return labels
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")
