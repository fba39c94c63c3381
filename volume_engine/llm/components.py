"""Connected components by contraction: every node joins its least neighbour, then the edges shrink."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise


def connected(edges: DataFrame, label: str = "components") -> DataFrame:
    """(node, root) for every node of ``edges`` (a, b); the root is the component's least node.

    Each round maps nodes to their least neighbour, follows that map twice and renames the edges,
    so components shrink by a constant factor at least; nothing is collected but "is it empty".
    """
    left = materialise(edges.select("a", "b").filter("a != b").distinct(), label)
    names: DataFrame | None = None
    while not left.isEmpty():
        both = left.unionByName(left.select(F.col("b").alias("a"), F.col("a").alias("b")))
        step = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("to")).select(F.col("a").alias("node"), "to")
        step = materialise(step, label)
        for _ in range(2):
            nxt = step.select(F.col("node").alias("to"), F.col("to").alias("further"))
            step = step.join(nxt, "to", "left").select("node", F.coalesce("further", "to").alias("to"))
        step = materialise(step, label)
        if names is None:
            names = step.select("node", F.col("to").alias("root"))
        else:
            hop = step.select(F.col("node").alias("root"), "to")
            names = materialise(names.join(hop, "root", "left").select("node", F.coalesce("to", "root").alias("root")), label)
        ends = left
        for side in ("a", "b"):
            ends = ends.join(step.select(F.col("node").alias(side), F.col("to").alias(f"{side}_to")), side).drop(side)
        left = materialise(ends.select(F.col("a_to").alias("a"), F.col("b_to").alias("b")).filter("a != b").distinct(), label)
    if names is None:
        return left.select(F.col("a").alias("node"), F.col("b").alias("root"))
    return names
