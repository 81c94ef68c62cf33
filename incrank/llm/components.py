"""Connected components of a table of links, with joins and aggregates only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored


def connected_components(links: DataFrame) -> DataFrame:
    """node, component of every node of ``links`` (a, b): the component is its smallest node.

    Each round takes the least label among a node's neighbours and then that label's own label, so that labels travel along
    chains in ever longer jumps, until none changes. Labels are written after each round; the driver sees one count.
    """
    both = stored(links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct(), "links")
    labels = stored(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("component")).withColumnRenamed("a", "node"), "labels")
    while True:
        near = both.join(labels.withColumnRenamed("node", "b"), "b").groupBy("a").agg(F.min("component").alias("near")).withColumnRenamed("a", "node")
        step = labels.join(near, "node").select("node", F.col("component").alias("was"), F.least("component", "near").alias("to"))
        up = labels.select(F.col("node").alias("to"), F.col("component").alias("further"))
        jumped = stored(step.join(up, "to", "left").select("node", "was", F.least("to", "further").alias("component")), "labels")
        labels = jumped.select("node", "component")
        if not jumped.where("component < was").limit(1).count():
            return labels
