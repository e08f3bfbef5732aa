"""Connected components of a graph that is a DataFrame of links."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import cut


def components(links: DataFrame) -> DataFrame:
    """(node, root) for every node of ``links`` (src, dst), any orderable type; root is the smallest node reachable.

    Each round takes the smallest label among neighbours and then the label's own
    label, so rounds grow with the logarithm of a component's width. Every round is
    checkpointed; neither links nor labels reach the driver. No links, no rows.
    """
    both = cut(links.select("src", "dst").union(links.select(F.col("dst"), F.col("src"))).where("src <> dst").distinct())
    labels = cut(both.groupBy(F.col("src").alias("node")).agg(F.min("dst").alias("least")).select("node", F.least("node", "least").alias("root")))
    while True:
        heard = both.join(labels.withColumnRenamed("node", "dst"), "dst").groupBy(F.col("src").alias("node")).agg(F.min("root").alias("heard"))
        nearer = labels.join(heard, "node").select("node", F.col("root").alias("was"), F.least("root", "heard").alias("root"))
        up = labels.select(F.col("node").alias("root"), F.col("root").alias("above"))
        labels_next = cut(nearer.join(up, "root").select("node", "was", F.least("root", "above").alias("root")))
        done = labels_next.where("root <> was").isEmpty()
        labels = labels_next.select("node", "root")
        if done:
            return labels
