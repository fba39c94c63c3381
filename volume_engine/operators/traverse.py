"""Descent to the node that stands for a place: three ways to find it, and one tree per channel as baseline.

All take the keys of wanted places at level 0 (key) and a tree without the nodes that pruning or an
unfinished build left out (level, key); they give the level of the finest node on the way down from the root.
The root is always there.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .fullframe import slots_side

#: Nodes that may be sent to every task as sorted arrays.
MOST_SORTED = 1 << 20


def locate_by_key(wanted: DataFrame, tree: DataFrame, top: int) -> DataFrame:
    """key, level by an equi-join of all ancestors of the wanted places: for any size of tree."""
    up = wanted.select("key", F.explode(F.sequence(F.lit(0), F.lit(top))).alias("level")).withColumn("at", F.expr("shiftright(key, 3 * level)"))
    found = up.join(tree.select("level", F.col("key").alias("at")), ["level", "at"])
    return found.groupBy("key").agg(F.min("level").alias("level"))


def locate_by_level(wanted: DataFrame, tree: DataFrame, top: int) -> DataFrame:
    """The same by one join per level, coarse levels first sent to all tasks: no more rows than there are places."""
    out, level = wanted.select("key"), F.lit(top)
    hits = []
    for l in range(top, -1, -1):
        side = tree.filter(F.col("level") == l).select(F.col("key").alias(f"k{l}"), F.lit(l).alias(f"l{l}"))
        out = out.join(slots_side(side), F.expr(f"shiftright(key, {3 * l})") == F.col(f"k{l}"), "left").drop(f"k{l}")
        hits.append(f"l{l}")
    level = F.coalesce(*(F.col(h) for h in reversed(hits)), level)
    return out.select("key", level.cast("int").alias("level"))


def locate_sorted(wanted: DataFrame, tree: DataFrame, top: int) -> DataFrame:
    """The same by binary search in sorted keys per level that every task holds; for trees of at most ``MOST_SORTED`` nodes."""
    if tree.count() > MOST_SORTED:
        raise ValueError("the tree is too large to be sent to every task")
    rows = tree.select("level", "key").toArrow()
    levels, keys = rows["level"].to_numpy(), rows["key"].to_numpy()
    held = wanted.sparkSession.sparkContext.broadcast([np.sort(keys[levels == l]) for l in range(top + 1)])

    def run(batches):
        for batch in batches:
            key = batch["key"].to_numpy()
            level = np.full(len(key), top, dtype=np.int32)
            for l in range(top, -1, -1):
                nodes = held.value[l]
                if len(nodes):
                    at = np.minimum(np.searchsorted(nodes, key >> (3 * l)), len(nodes) - 1)
                    level[nodes[at] == key >> (3 * l)] = l
            yield pa.record_batch({"key": batch["key"], "level": pa.array(level)})

    return wanted.select("key").mapInArrow(run, "key long, level int")


def locate_per_channel(wanted: DataFrame, trees: DataFrame, top: int) -> DataFrame:
    """key, c, level with a tree per channel (c, level, key): every place is looked up once for each channel."""
    up = wanted.select("key", F.explode(F.sequence(F.lit(0), F.lit(top))).alias("level")).withColumn("at", F.expr("shiftright(key, 3 * level)"))
    found = up.join(trees.select("c", "level", F.col("key").alias("at")), ["level", "at"])
    return found.groupBy("key", "c").agg(F.min("level").alias("level"))


def channel_trees(bricks: DataFrame, channels: int, threshold: float) -> DataFrame:
    """(c, level, key) of one collapsed tree per channel over the inserted bricks."""
    rows = bricks.select("level", "key", F.explode(F.expr(f"filter(transform(sequence(0, {channels - 1}), c -> struct(c as c, known[c] as known, smax[c] - smin[c] as span)), s -> s.known > 0)")).alias("s"))
    rows = rows.select("s.c", "level", "key", (F.col("s.span") < threshold).alias("flat"))
    gone = rows.filter("flat").select("c", (F.col("level") - 1).alias("level"), F.col("key").alias("parent"))
    return rows.withColumn("parent", F.shiftright("key", 3)).join(gone, ["c", "level", "parent"], "left_anti").select("c", "level", "key")
