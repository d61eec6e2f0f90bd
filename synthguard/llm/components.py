"""Connected components of a graph given by its edges."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from synthguard.llm.common import staged, unstaged


def components(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """node, comp (the smallest node of its component) of every node with an edge (a, b).

    Every node points to its smallest neighbour; then the edges are drawn between those and each node's pointers are followed, until
    nothing moves: each round joins and pre-aggregates, so no node's neighbours meet in one task, and distances at least halve on paths.
    """
    both = edges.select(F.col("a").alias("node"), F.col("b").alias("to")).unionByName(edges.select(F.col("b").alias("node"), F.col("a").alias("to")))
    links = staged(spark, both.where("node <> to").distinct(), "links")
    labels = staged(spark, links.groupBy("node").agg(F.least(F.min("to"), F.col("node")).alias("comp")), "labels")
    while True:
        # the smallest label among the neighbours, and then the label of one's label
        near = links.join(labels.select(F.col("node").alias("to"), F.col("comp").alias("c")), "to").groupBy("node").agg(F.min("c").alias("c"))
        lower = labels.select("node", "comp").join(near, "node").select("node", F.least("comp", "c").alias("new"), F.col("comp").alias("old"))
        # a label's own node hears of the smaller label that one of its members has met
        told = lower.where("new < old").groupBy(F.col("old").alias("node")).agg(F.min("new").alias("heard"))
        once = lower.join(told, "node", "left").select("node", F.least("new", F.coalesce("heard", "new")).alias("new"), "old")
        once, before = staged(spark, once, "labels"), labels
        jump = once.select(F.col("node").alias("new"), F.col("new").alias("further"))
        labels = staged(spark, once.join(jump, "new", "left").select("node", F.least("new", F.coalesce("further", "new")).alias("comp"), "old"), "labels")
        moved = not labels.where("comp <> old").isEmpty()
        unstaged(spark, once, before)
        if not moved:
            unstaged(spark, links)
            return labels.select("node", "comp")
