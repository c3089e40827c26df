"""Connected components."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.shared import settle


def connected(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) for the nodes of undirected edges (a, b); root is the component's smallest node.

    Labels move to the smallest neighbouring label, then to that label's own label (which halves chains); only minima
    travel.  Each round is checkpointed.
    """
    both = settle(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a != b").distinct())
    labels = settle(both.select(F.col("a").alias("node")).distinct().withColumn("root", F.col("node")))
    for _ in range(max_rounds):
        near = both.join(labels, F.col("b") == F.col("node")).groupBy("a").agg(F.min("root").alias("m"))
        hooked = labels.join(near, F.col("node") == F.col("a")).select("node", F.least("root", "m").alias("root"), F.col("root").alias("old"))
        up = hooked.select(F.col("node").alias("n2"), F.col("root").alias("r2"))
        new = settle(hooked.join(up, F.col("root") == F.col("n2"), "left").select("node", F.least("root", F.coalesce("r2", "root")).alias("root"), "old"))
        if new.where("root != old").isEmpty():
            return new.select("node", "root")
        labels = new.select("node", "root")
    raise RuntimeError("connected: rounds used up")
