"""Connected components by minimum labels with pointer jumping."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import discard


def connected_components(edges: DataFrame, store: Callable[[DataFrame], DataFrame], src: str = "src", dst: str = "dst", max_rounds: int = 200) -> DataFrame:
    """(node, component) for every node of an edge: the smallest node that can be reached.

    Nodes of equal label form a group. A round gives every group the least label next to any of its nodes, and then
    that label's own new one, so groups merge as wholes and paths halve. `store` writes a table and reads it back,
    which ends the lineage of each round; what a round no longer needs is deleted. Neighbours are reduced before each shuffle. The driver sees counts.
    """
    pairs = edges.select(F.col(src).alias("u"), F.col(dst).alias("v"))
    both = store(pairs.unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct())
    labels = store(both.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("m")).select("node", F.least("node", "m").alias("component")))
    for _ in range(max_rounds):
        near = both.join(labels.select(F.col("node").alias("v"), F.col("component").alias("c")), "v").groupBy("u").agg(F.min("c").alias("c"))
        low = labels.join(near, labels["node"] == near["u"]).select(F.col("component").alias("old"), F.least("component", "c").alias("c"))
        moves = store(low.groupBy("old").agg(F.min("c").alias("c")).filter("c < old"))
        if moves.isEmpty():
            discard(both, moves)
            return labels
        onward = moves.select(F.col("old").alias("at"), F.col("c").alias("further"))
        jumps = moves.join(onward, moves["c"] == onward["at"], "left").select("old", F.coalesce("further", "c").alias("to"))
        before = labels
        labels = store(labels.join(jumps, labels["component"] == jumps["old"], "left").select("node", F.coalesce("to", "component").alias("component")))
        discard(before, moves)
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
