"""Connected components of an edge table, in DataFrame operations."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written


def connected_components(edges: DataFrame, *, max_rounds: int = 60) -> DataFrame:
    """node, component (its smallest node) for the nodes of edges (a, b).

    Every round each node takes the smallest label among its own, its
    neighbours' and its label's label, so chains shorten by halves.  Where a
    node left a label for a smaller one, the next round moves all nodes of the
    old label along, so that trees join whole instead of a node a round.
    Labels are written to the shared folder each round; nothing reaches the
    driver but whether any changed.
    """
    both = written(
        edges.select("a", "b").union(edges.select("b", "a")).where("a <> b").distinct(), "component-edges"
    )
    labels = written(
        both.groupBy("a").agg(F.min("b").alias("low")).select(
            F.col("a").alias("node"), F.col("a").alias("old"), F.least("a", "low").alias("component")
        ),
        "component-labels",
    )
    for _ in range(max_rounds):
        near = both.join(labels, both.b == labels.node).groupBy("a").agg(F.min("component").alias("low"))
        left = labels.where("component < old").groupBy("old").agg(F.min("component").alias("hook"))
        jump = labels.select(F.col("node").alias("at"), F.col("component").alias("own")).join(left, F.col("at") == F.col("old"), "left")
        jump = jump.select("at", F.least("own", "hook").alias("next"))
        stepped = (
            labels.join(near, labels.node == near.a)
            .select("node", F.col("component").alias("old"), F.least("component", "low").alias("label"))
            .join(jump, F.col("label") == F.col("at"), "left")
            .select("node", "old", F.least("label", "next").alias("component"))
        )
        labels = written(stepped, "component-labels")
        if labels.where("old <> component").isEmpty():
            return labels.select("node", "component")
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
