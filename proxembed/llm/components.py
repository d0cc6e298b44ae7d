"""Connected components of stored links, by minimum labels and pointer jumping; every round is a stored table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxembed.llm.common import store


def components(edges: DataFrame) -> DataFrame:
    """(a, b) links -> (node, label), label the smallest node reachable. Nodes without links are absent.

    A round passes labels over links (partial minima before each shuffle, so hubs don't pile up) and then lets each
    node take its label's label, which halves the distance to the root.
    """
    both = store(edges.select(F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b")))).alias("e")).select("e.*").where("a <> b").distinct(), "links")
    labels = store(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("label")), "labels")
    while True:
        heard = both.join(labels.select(F.col("node").alias("b"), "label"), "b").groupBy(F.col("a").alias("node")).agg(F.min("label").alias("heard"))
        near = labels.join(heard, "node").select("node", F.col("label").alias("old"), F.least("label", "heard").alias("label"))
        roots = labels.select(F.col("node").alias("label"), F.col("label").alias("root"))
        jumped = store(near.join(roots, "label").select("node", F.least("label", "root").alias("label"), "old"), "labels")
        labels = jumped.select("node", "label")
        if jumped.where("label <> old").isEmpty():
            return labels
