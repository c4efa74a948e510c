"""Connected components of an edge table, by smallest labels and pointer jumping."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, stored

MOST_ROUNDS = 60


def components(edges: DataFrame) -> DataFrame:
    """edges (a long, b long) -> (node, root): the smallest node that each node of an edge reaches.

    Every round is written to the shared folder; a round costs two joins and an aggregate over nodes and edges, and
    the number of rounds follows the logarithm of the longest path.
    """
    both = stored(edges.select("a", "b").union(edges.select("b", "a")).distinct(), "cc-edges")
    labels = stored(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("low")).select("node", F.least("node", "low").alias("root")), "cc-labels")
    for _ in range(MOST_ROUNDS):
        heard = both.join(labels.withColumnRenamed("node", "b"), "b").select(F.col("a").alias("node"), "root")
        lower = heard.unionByName(labels).groupBy("node").agg(F.min("root").alias("root"))
        lower = stored(lower, "cc-lower")
        above = lower.select(F.col("node").alias("root"), F.col("root").alias("top"))
        jumped = stored(lower.join(above, "root").select("node", F.least("root", "top").alias("root")), "cc-labels")
        done = jumped.join(labels.withColumnRenamed("root", "was"), "node").where("root <> was").isEmpty()
        discard(lower)
        discard(labels)
        labels = jumped
        if done:
            discard(both)
            return labels
    raise RuntimeError(f"labels still change after {MOST_ROUNDS} rounds")
