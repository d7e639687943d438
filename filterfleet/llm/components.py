"""Connected components of a table of links, by rounds of joins; nothing of it comes to the driver but counts."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from filterfleet.llm.common import materialize


def components(links: DataFrame) -> DataFrame:
    """(node, label) from (a, b): label is the smallest node that links reach, the node itself included.

    Each round a node takes the smallest label among its own and its neighbours' (a combining aggregation, so a node
    with very many links is summed up before the shuffle), then the label of its label, which halves paths.
    """
    both = materialize(links.select("a", "b").unionByName(links.selectExpr("b as a", "a as b")).where("a <> b").distinct(), "links")
    labels = both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("low")).selectExpr("node", "least(node, low) as label")
    while True:
        labels = materialize(labels, "labels")
        near = both.join(labels.withColumnRenamed("node", "b"), "b").groupBy(F.col("a").alias("node")).agg(F.min("label").alias("low"))
        lower = labels.join(near, "node").selectExpr("node", "label", "least(label, low) as next")
        up = labels.selectExpr("node as next", "label as above")
        moved = materialize(lower.join(up, "next", "left").selectExpr("node", "label", "least(next, coalesce(above, next)) as next"), "labels")
        if not moved.where("next < label").limit(1).count():
            return labels
        labels = moved.selectExpr("node", "next as label")
