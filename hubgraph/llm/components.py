"""Connected components of a graph held in DataFrames: smallest label, neighbour step plus pointer jump."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubgraph.llm.common import stage


def connected_components(edges: DataFrame) -> DataFrame:
    """(a, b) edges to (node, label): label is the smallest node that is reachable.

    Each round takes the smallest label of the neighbours and then the label of that label, so that chains
    shrink by halves. Every round is written out; nothing but a count of changed rows reaches the driver.
    """
    both = stage(edges.select("a", "b").union(edges.select(F.col("b"), F.col("a"))).where("a <> b").distinct())
    labels = stage(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("label")))
    while True:
        near = both.join(labels.select(F.col("node").alias("b"), "label"), "b").groupBy(F.col("a").alias("node")).agg(F.min("label").alias("near"))
        stepped = labels.join(near, "node").select("node", F.col("label").alias("old"), F.least("label", "near").alias("new"))
        jump = labels.select(F.col("node").alias("new"), F.col("label").alias("far"))
        moved = stage(stepped.join(jump, "new", "left").select("node", "old", F.least("new", F.coalesce("far", "new")).alias("label")))
        changed = moved.where("label <> old").limit(1).count()
        labels = moved.select("node", "label")
        if not changed:
            return labels
