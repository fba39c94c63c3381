"""Octree nodes over brick statistics: homogeneity of bricks and subtrees, collapse and per-channel trees."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.grid import VolumeMeta, bfs_index, morton3


def build_nodes(stats: DataFrame, vm: VolumeMeta, threshold: float) -> DataFrame:
    """One row per brick: channel averages, and whether brick and subtree are homogeneous in every channel (strictly below ``threshold``).

    A channel without a row is background throughout, hence homogeneous.
    """
    g = stats.groupBy("level", "ix", "iy", "iz").agg(
        F.max(F.col("bmax") - F.col("bmin")).alias("spread"), F.max(F.col("smax") - F.col("smin")).alias("subspread"), F.max("n").alias("n"),
        *(F.coalesce(F.max(F.when(F.col("c") == c, F.col("avg"))), F.lit(vm.background)).alias(f"avg{c}") for c in range(vm.channels)),
    )
    key = morton3(F.col("ix"), F.col("iy"), F.col("iz"), vm.key_bits)
    return g.withColumns({"key": key, "homog": F.col("spread") < threshold, "subhomog": F.col("subspread") < threshold})


def nodes_of_bricks(bricks: DataFrame, vm: VolumeMeta, threshold: float | list[float]) -> DataFrame:
    """The same from bricks of a pool, a projection of their statistics; a list gives one threshold per channel."""
    limits = [float(t) for t in threshold] if isinstance(threshold, list) else [float(threshold)] * vm.channels
    below = "forall(zip_with(zip_with({0}max, {0}min, (p, q) -> p - q), array(" + ", ".join(f"{t!r}D" for t in limits) + "), (d, t) -> d < t), s -> s)"
    spread = "array_max(zip_with({0}max, {0}min, (p, q) -> p - q))"
    return bricks.select(
        "level", "key", "ix", "iy", "iz", "n", F.expr(spread.format("b")).alias("spread"), F.expr(spread.format("s")).alias("subspread"),
        *(F.expr(f"bsum[{c}] div n").alias(f"avg{c}") for c in range(vm.channels)), F.expr(below.format("b")).alias("homog"), F.expr(below.format("s")).alias("subhomog"),
    )


def collapse(nodes: DataFrame, vm: VolumeMeta) -> DataFrame:
    """Nodes that survive: those whose parent's subtree is not homogeneous, with idx and has_brick."""
    gone = nodes.filter("subhomog").select((F.col("level") - 1).alias("level"), F.col("key").alias("pkey"))
    kept = nodes.withColumn("pkey", F.shiftright("key", 3)).join(gone, ["level", "pkey"], "left_anti")
    return kept.withColumns({"has_brick": ~F.col("homog"), "leaf": F.col("subhomog") | (F.col("level") == 0), "idx": bfs_index(F.col("level"), F.col("key"), vm.top)}).drop("pkey")


def pack_sparse(bricks: DataFrame, vm: VolumeMeta, threshold: float) -> DataFrame:
    """Bricks that keep only their channels that are not homogeneous: level, key, present (bits), body and avg.

    ``body`` holds the kept channels interleaved, so bodies differ in size; the others are their averages.
    """
    kept = F.expr(f"filter(sequence(0, {vm.channels - 1}), c -> bmax[c] - bmin[c] >= {float(threshold)!r}D)")
    rows = bricks.select("level", "key", "body", F.expr("transform(bsum, s -> s div n)").alias("avg"), kept.alias("channels"))
    present = F.expr("aggregate(channels, 0, (a, c) -> a | shiftleft(1, c))")
    body = F.expr(f"filter(body, (v, i) -> array_contains(channels, cast(i % {vm.channels} as int)))")
    return rows.select("level", "key", present.alias("present"), F.when(F.size("channels") == vm.channels, F.col("body")).otherwise(body).alias("body"), "avg")


def error_level(nodes: DataFrame, vm: VolumeMeta, tolerance: float) -> DataFrame:
    """For every leaf key, the coarsest level whose whole subtree varies by less than ``tolerance`` (0 if none does): key, level.

    The level choice by error instead of by distance; a level is told by the spread of what it stands for.
    """
    flat = nodes.filter(F.col("subspread") < tolerance).select("level", F.col("key").alias("at"))
    up = nodes.filter("level = 0").select("key", F.explode(F.sequence(F.lit(0), F.lit(vm.top))).alias("level")).withColumn("at", F.expr("shiftright(key, 3 * level)"))
    found = up.join(flat.withColumn("hit", F.lit(1)), ["level", "at"], "left")
    return found.groupBy("key").agg(F.coalesce(F.max(F.when(F.col("hit") == 1, F.col("level"))), F.lit(0)).alias("level"))


def siblings(kept: DataFrame) -> DataFrame:
    """Background nodes (level, key) that complete the eight children of every collapsed node that has any."""
    children = kept.filter("not leaf").select((F.col("level") - 1).alias("level"), F.col("key").alias("parent"))
    children = children.withColumn("octant", F.explode(F.sequence(F.lit(0), F.lit(7)))).select("level", (F.shiftleft("parent", 3) + F.col("octant")).alias("key"))
    return children.join(kept.select("level", "key"), ["level", "key"], "left_anti")


def level_summary(nodes: DataFrame) -> DataFrame:
    return nodes.groupBy("level").agg(F.count("*").alias("bricks"), F.count_if("homog").alias("homogeneous"), F.count_if("subhomog").alias("subtrees"))


def threshold_sweep(nodes: DataFrame, thresholds: list[float]) -> DataFrame:
    """Stored bricks per threshold: one pass against a small literal table."""
    spark = nodes.sparkSession
    sweep = F.broadcast(spark.createDataFrame([(float(t),) for t in thresholds], "threshold double"))
    return nodes.join(sweep).groupBy("threshold").agg(F.count("*").alias("bricks"), F.count_if(F.col("spread") >= F.col("threshold")).alias("stored"))
