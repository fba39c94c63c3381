"""Incremental construction: blocks arrive in any order, may overwrite, and only their ancestors are recomputed."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.grid import AXES, VolumeMeta, coords
from .pool import STATS, BrickPool

CELL = [*AXES, "c"]


def latest(log: DataFrame, order: str = "seq") -> DataFrame:
    """Last writer wins per voxel and channel of an insertion log (x, y, z, c, v, seq)."""
    return log.groupBy(*CELL).agg(F.max_by("v", order).alias("v"))


def insert_blocks(pool: BrickPool, log: DataFrame, per_block: int | None = None, axis: str = "z") -> int:
    """Insert a log (x, y, z, c, v, seq) into a pool, the last writer winning; return the number of versions made.

    ``per_block`` cuts the log into one block per that many slices of an axis, in order, as a scanner
    would send them; without it the whole log is one block, and ancestors are rewritten once.
    """
    cells = latest(log)
    if per_block is None:
        pool.insert(cells)
        return 1
    blocks = [r[0] for r in cells.select(F.expr(f"{axis} div {per_block}").alias("b")).distinct().orderBy("b").collect()]  # a row per block of slices
    for b in blocks:
        pool.insert(cells.filter(f"{axis} div {per_block} = {b}"))
    return len(blocks)


def interleaved(parts: list[DataFrame], vm: VolumeMeta) -> DataFrame:
    """Bricks of one channel each put together; a channel without a brick is unknown there, hence background."""
    at = ["level", "key", "ix", "iy", "iz", "n"]
    out = None
    for c, part in enumerate(parts):
        own = part.select(*at, *(F.col(k).alias(f"{k}_{c}") for k in ("body", *STATS)))
        out = own if out is None else out.join(own, at, "full")
    cells, bg = vm.brick[0] * vm.brick[1] * vm.brick[2], vm.background
    bodies = ", ".join(f"coalesce(body_{c}, array_repeat(cast(null as int), {cells}))" for c in range(len(parts)))
    body = F.expr(f"flatten(transform(sequence(0, {cells - 1}), i -> transform(array({bodies}), b -> b[i])))")
    absent = {"known": "0L", "bsum": f"{bg}L * n"}
    stats = [F.expr("array(" + ", ".join(f"coalesce({s}_{c}[0], {absent.get(s, f'{bg}L')})" for c in range(len(parts))) + ")").alias(s) for s in STATS]
    return out.select(*at, body.alias("body"), *stats)


def build(voxels: DataFrame, vm: VolumeMeta, parallel: str = "none", path: str | None = None) -> BrickPool:
    """A pool of a whole volume by one of the ways to share the work out.

    ``shards``: the pool's own way, groups of bricks by ancestor.  ``channel``: one builder per channel,
    their bricks put together at the end.  ``octant``: one builder per octant of the root, with the
    ancestors they share made by a last step.  ``none``: one task.  All give the same bricks, and
    every builder goes through its bricks in groups of the same bounded size.
    """
    spark = voxels.sparkSession
    pool = BrickPool.create(spark, vm, path)
    if parallel == "shards":
        pool.insert(voxels)
    elif parallel == "channel":
        alone = replace(vm, channels=1)
        parts = [BrickPool.create(spark, alone) for _ in range(vm.channels)]
        with ThreadPoolExecutor(vm.channels) as builders:
            list(builders.map(lambda c: parts[c].insert(voxels.filter(F.col("c") == c).withColumn("c", F.lit(0))), range(vm.channels)))
        pool.commit(interleaved([p.bricks() for p in parts], vm))
    elif parallel == "octant":
        pool.insert(voxels, alone=max(vm.top - 1, 0))
    elif parallel == "none":
        pool.insert(voxels, alone=vm.top)
    else:
        raise ValueError(parallel)
    return pool


def touched_nodes(block: DataFrame, vm: VolumeMeta) -> DataFrame:
    """(level, ix, iy, iz) of every node on the insertion paths of a block's voxels."""
    out = block.select(F.lit(0).alias("level"), *(c.alias(k) for k, c in coords(0, vm).items())).distinct()
    all_levels = below = out
    for level in range(1, vm.top + 1):
        below = below.select(F.lit(level).alias("level"), *(F.expr(f"i{a} div 2").alias(f"i{a}") for a in AXES)).distinct()
        all_levels = all_levels.unionByName(below)
    return all_levels


def parent_updates(log: DataFrame, vm: VolumeMeta, slices_per_block: int = 1) -> DataFrame:
    """Brick rewrites per level when slices are inserted in groups of ``slices_per_block``."""
    rows = log.select(F.expr(f"z div {slices_per_block}").alias("block"), *(c.alias(k) for k, c in coords(0, vm).items()))
    levels = rows.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(vm.top))))
    up = levels.selectExpr("block", "level", *(f"i{a} div cast(power(2, level) as bigint) as i{a}" for a in AXES))
    return up.distinct().groupBy("level").agg(F.count("*").alias("updates"))
