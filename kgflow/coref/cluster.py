"""Connected components of a graph given as edges, by joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgflow.session import settled


def components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, label): label is the least node that can be reached.

    Every round, each node takes the least label among its neighbours and then the label of its
    label; labels only fall, and paths of labels halve. The neighbour minimum is a map-side
    combined aggregation, so a hub costs one row per task; lineage is cut in the shared folder
    each round. Rows with a null end are ignored; self-loops give single nodes."""
    pairs = edges.select(F.col(a).alias("a"), F.col(b).alias("b")).where("a is not null and b is not null")
    both = settled(pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    if both.isEmpty():
        return both.select(F.col("a").alias("node"), F.col("b").alias("label"))
    labels = settled(both.groupBy("a").agg(F.min("b").alias("n")).select(F.col("a").alias("node"), F.least("a", "n").alias("label")))
    for _ in range(max_rounds):
        near = both.join(labels, F.col("b") == F.col("node")).groupBy("a").agg(F.min("label").alias("near"))
        low = labels.join(near, F.col("node") == F.col("a")).select("node", F.col("label").alias("old"), F.least("label", "near").alias("label"))
        up = labels.select(F.col("node").alias("via"), F.col("label").alias("top"))
        nxt = settled(low.join(up, F.col("label") == F.col("via"), "left").select("node", "old", F.least("label", F.coalesce("top", "label")).alias("label")))
        moved = nxt.where("label <> old").limit(1).count()
        labels = nxt.select("node", "label")
        if not moved:
            return labels
    raise RuntimeError(f"labels still moved after {max_rounds} rounds")
