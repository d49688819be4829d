"""Connected components by hooking and pointer jumping on DataFrames; nothing but counts reaches the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coloc.llm.tables import Scratch, staged


def roots(parents: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """node, parent with parent < node, one row per node -> node, root, by doubling the jumps until none moves."""
    held = staged(parents.select("node", F.col("parent").alias("root")), "roots", scratch)
    while True:
        above = held.select(F.col("node").alias("up"), F.col("root").alias("over"))
        step = held.join(above, F.col("root") == F.col("up"), "left")
        held = staged(step.select("node", F.coalesce("over", "root").alias("root"), F.col("over").isNotNull().alias("moved")), "roots", scratch)
        if held.where("moved").isEmpty():
            return held.select("node", "root")
        held = held.select("node", "root")


def components(edges: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """Edges (a, b) -> node, root for every node of an edge with a <> b; root is the smallest node of its component.

    Each round hooks every component that has a smaller neighbour below the smallest; of neighbouring components at least
    one hooks, so their number halves.
    """
    left = staged(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges", scratch)
    labels = staged(left.select(F.explode(F.array("a", "b")).alias("node")).distinct().withColumn("root", F.col("node")), "labels", scratch)
    while not left.isEmpty():
        up = roots(left.groupBy(F.col("b").alias("node")).agg(F.min("a").alias("parent")), scratch)
        moved = up.select(F.col("node").alias("old"), F.col("root").alias("new"))
        labels = staged(labels.join(moved, F.col("root") == F.col("old"), "left").select("node", F.coalesce("new", "root").alias("root")), "labels", scratch)
        one = left.join(moved, F.col("a") == F.col("old"), "left").select(F.coalesce("new", "a").alias("a"), "b")
        two = one.join(moved, F.col("b") == F.col("old"), "left").select("a", F.coalesce("new", "b").alias("b"))
        left = staged(two.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges", scratch)
    return labels
