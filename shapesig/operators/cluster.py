"""Clusters of linked shapes: components of an edge table that is never collected."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shapesig.session import settle


def clusters(links: DataFrame, rounds: int = 50) -> DataFrame:
    """(node, cluster) for every node of ``links`` (a, b): the least node that links reach.

    Each round gives a node the least label around it and then its label's own label,
    so that distances halve; a count of changed labels is all that comes to the driver.
    """
    edges = settle(links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct())
    label = settle(edges.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("cluster")).withColumnRenamed("a", "node"))
    for _ in range(rounds):
        around = edges.join(label.withColumnRenamed("node", "b"), "b").groupBy(F.col("a").alias("node")).agg(F.min("cluster").alias("near"))
        hop = label.select(F.col("node").alias("cluster"), F.col("cluster").alias("far"))
        new = label.join(around, "node").join(hop, "cluster").select("node", F.least("cluster", "near", "far").alias("next"), "cluster")
        new = settle(new)
        label = new.select("node", F.col("next").alias("cluster"))
        if new.where("next <> cluster").isEmpty():
            return label
    raise RuntimeError("clusters did not settle")
