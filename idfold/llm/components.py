"""Connected components of a link table by least labels with pointer jumping."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from idfold.llm.common import settle


def components(links: DataFrame) -> DataFrame:
    """(node, label) for every node of ``links(a, b)``; label is the least node reachable.

    Links are taken in both directions. Each round takes the least label among a node's neighbours
    and then the label of that label, so chains shorten geometrically. Labels are written out in
    the shared folder every round; only one number per round comes to the driver.
    """
    both = links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a != b").distinct()
    both = settle(both)
    labels = settle(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("label")))
    while True:
        near = both.join(labels.select(F.col("node").alias("b"), F.col("label").alias("m")), "b").groupBy("a").agg(F.min("m").alias("m"))
        lower = labels.join(near.withColumnRenamed("a", "node"), "node").select("node", F.col("label").alias("old"), F.least("label", "m").alias("label"))
        up = labels.select(F.col("node").alias("label"), F.col("label").alias("above"))
        after = settle(lower.join(up, "label").select("node", "old", F.least("label", "above").alias("label")))
        if after.where("label != old").isEmpty():
            return after.select("node", "label")
        labels = after.select("node", "label")
