"""Connected components by contraction, for small and large edge tables alike."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from roadtraj.plans.scratch import cut


def components(edges: DataFrame) -> DataFrame:
    """node, label (one node of its component) of the nodes of undirected edges a, b.

    In each round nodes move onto their smallest neighbour, and only edges between
    different places go on; the places of all rounds lead to the label.
    """
    left = cut(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a <> b").distinct())
    moves = []
    while True:
        both = left.union(left.select("b", "a")).groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m"))
        move = cut(both.select("node", F.least("node", "m").alias("to")))
        moves.append(move)
        ends = [move.select(F.col("node").alias(c), F.col("to").alias(f"_{c}")) for c in "ab"]
        moved = left.join(ends[0], "a").join(ends[1], "b").where("_a <> _b")
        left = cut(moved.select(F.least("_a", "_b").alias("a"), F.greatest("_a", "_b").alias("b")).distinct())
        if left.isEmpty():
            break
    labels = moves[-1].select("node", F.col("to").alias("label"))
    for move in reversed(moves[:-1]):
        labels = move.join(labels.withColumnRenamed("node", "to"), "to", "left").select("node", F.coalesce("label", "to").alias("label"))
    return labels
