"""Connected components of a graph of 64-bit nodes, by spreading least labels with pointer jumping.

All state is in tables in the shared folder; each round is written, so lineage stays short and a lost executor costs one round. Least labels
are combined before they are shuffled, and what nodes of high degree or large components have to tell is sent to every task, so none collects in one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shared


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """edges: a, b. Returns node, label: the least node that each node is connected to."""
    both = shared.keep(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    labels = shared.keep(both.groupBy(F.col("a").alias("node")).agg(F.min(F.least("a", "b")).alias("label"), F.count("*").alias("degree")), "labels")
    ends, nodes = both.count(), labels.count()
    for _ in range(max_rounds):
        told = labels.select(F.col("node").alias("b"), "label", "degree")
        heard = shared.meet(both, told, "b", "degree", ends).groupBy(F.col("a").alias("node")).agg(F.min("label").alias("heard"))
        # the label's own label: one jump along the pointers
        size = labels.groupBy("label").agg(F.count("*").alias("n"))
        hop = labels.select(F.col("node").alias("label"), F.col("label").alias("far")).join(size, "label")
        joined = shared.meet(labels, hop, "label", "n", nodes).join(heard, "node")
        new = shared.keep(joined.select("node", F.col("label").alias("old"), F.least("label", "far", "heard").alias("label"), "degree"), "labels")
        moved = new.where("label <> old").limit(1).count()
        labels = new.select("node", "label", "degree")
        if not moved:
            return labels.select("node", "label")
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
