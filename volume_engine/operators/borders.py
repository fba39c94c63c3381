"""Brick borders apart from building: the deferred job over a finished pool, the cost of eager borders, and filtering across levels."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import storage
from ..functions.grid import AXES, VolumeMeta, coords
from .filtering import trilinear
from .fullframe import halo_voxels
from .pool import BrickPool


def level_meta(vm: VolumeMeta, level: int) -> VolumeMeta:
    """The declaration of a level as a volume of its own."""
    return VolumeMeta(f"{vm.name}-{level}", vm.at_level(level), vm.brick, vm.channels, vm.background, vm.lo, vm.hi, vm.voxel_bytes)


def border_job(pool: BrickPool, sides: int = 2, path: str | None = None) -> DataFrame:
    """Border voxels (level, ix, iy, iz, x, y, z, c, v) of every level of a finished pool, written beside it.

    Run once the tree is stable; building neither waits for it nor loads neighbours.  Each level is a
    scan of its bricks and one exchange.
    """
    path = path or f"{pool.path}/borders-{sides}-{pool.commits[-1] if pool.commits else 'none'}"
    if not storage.exists(pool.spark, f"{path}/_SUCCESS"):
        levels = (halo_voxels(pool.voxels(level=l).drop("level"), level_meta(pool.vm, l), sides).select(*(F.col(f"i{a}").cast("int") for a in AXES), *AXES, "c", "v", F.lit(l).alias("level")) for l in range(pool.vm.top + 1))
        reduce(DataFrame.unionByName, levels).write.mode("overwrite").partitionBy("level").parquet(path)
    return pool.spark.read.schema("ix int, iy int, iz int, x int, y int, z int, c int, v long, level int").parquet(path)


def eager_border_updates(log: DataFrame, vm: VolumeMeta, slices_per_block: int = 1) -> DataFrame:
    """Per level, the bricks that eager borders would write again on top of the path: neighbours of rewritten bricks (level, neighbours).

    The measure of why borders are deferred: each block loads them at every level.
    """
    rows = log.select(F.expr(f"z div {slices_per_block}").alias("block"), *(c.alias(k) for k, c in coords(0, vm).items())).distinct()
    steps = [F.lit(s) for s in (-1, 0, 1)]
    out = []
    for level in range(vm.top + 1):
        own = rows.select("block", *(F.expr(f"shiftright(i{a}, {level})").alias(f"i{a}") for a in AXES)).distinct()
        near = own
        for a, n in zip(AXES, vm.bricks_at(level), strict=True):
            near = near.withColumn("s", F.explode(F.array(*steps))).withColumn(f"i{a}", F.col(f"i{a}") + F.col("s")).drop("s").filter(f"i{a} >= 0 and i{a} < {n}")
        near = near.distinct().join(own, ["block", "ix", "iy", "iz"], "left_anti")
        out.append(near.agg(F.count("*").alias("neighbours")).withColumn("level", F.lit(level)))
    return reduce(DataFrame.unionByName, out)


def cross_level(samples: DataFrame, pool: BrickPool, blend: str = "f") -> DataFrame:
    """px, py, i, c, v filtered across two levels: trilinear at level 0 and at level 1, blended by the column ``blend`` in [0, 1]."""
    fine = trilinear(samples, pool.voxels(level=0).drop("level"), pool.vm)
    at = {a: (F.col(a) + F.col(f"f{a}") + 0.5) / 2 - 0.5 for a in AXES}
    halved = samples.select("px", "py", "i", blend, *(F.greatest(F.lit(0.0), c).alias(f"q{a}") for a, c in at.items()))
    halved = halved.select("px", "py", "i", *(F.floor(f"q{a}").cast("int").alias(a) for a in AXES), *((F.col(f"q{a}") - F.floor(f"q{a}")).alias(f"f{a}") for a in AXES))
    coarse = trilinear(halved, pool.voxels(level=1).drop("level"), level_meta(pool.vm, 1)).withColumnRenamed("v", "w")
    both = fine.join(coarse, ["px", "py", "i", "c"], "full").join(samples.select("px", "py", "i", blend), ["px", "py", "i"])
    mixed = (1 - F.col(blend)) * F.coalesce("v", F.lit(0.0)) + F.col(blend) * F.coalesce("w", F.lit(0.0))
    return both.select("px", "py", "i", "c", mixed.alias("v"))
