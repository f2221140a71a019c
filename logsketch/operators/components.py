"""Connected components by joins: every round stays distributed, and its table is written before the next."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..tables import release, table


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """edges (a, b) -> (node, component): the smallest node that can be reached.

    Each round links every node to the smallest label near it, then follows that label once more, so that long
    chains halve. Null ends and loops are left out; no edges give no rows.
    """
    both = edges.where("a is not null and b is not null and a <> b").select("a", "b")
    both = table(both.unionByName(both.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "links")
    labels = table(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.col("a")).alias("component")), "labels-0")
    for k in range(1, most_rounds):
        near = both.join(labels, both.b == labels.node).groupBy("a").agg(F.min("component").alias("near"))
        next_ = labels.join(near, labels.node == near.a, "left").select("node", F.least("component", "near").alias("component"), F.col("component").alias("was"))
        hop = labels.select(F.col("node").alias("at"), F.col("component").alias("to"))
        next_ = next_.join(hop, next_.component == hop["at"], "left").select("node", F.least("component", "to").alias("component"), "was")
        next_ = table(next_, f"labels-{k}")
        moved = next_.where("component <> was").limit(1).count()
        release(labels)
        labels = next_.select("node", "component")
        if not moved:
            break
    else:
        raise RuntimeError("components did not settle")
    return labels
