"""Joins that Spark has no operator for: boxes that overlap bricks, and the last row as of a moment."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.grid import AXES, VolumeMeta


def bricks_in_boxes(bricks: DataFrame, boxes: DataFrame, vm: VolumeMeta, level: int) -> DataFrame:
    """(box, key, ix, iy, iz) of the bricks of a level that overlap closed boxes (box, x0, y0, z0, x1, y1, z1) of level-0 voxels.

    Boxes are cut into cells of a few bricks an axis; bricks meet them by equality of their cell, and a
    residual condition decides.  A box of many cells makes many rows, so the cell grows with the largest box.
    """
    side = [m << level for m in vm.brick]
    most = boxes.agg(*(F.max(F.col(f"{a}1") - F.col(f"{a}0")) for a in AXES)).first()
    width = [max(s, s * -(-((w or 0) + 1) // (2 * s))) for s, w in zip(side, most, strict=True)]
    cut = boxes
    for a, w in zip(AXES, width, strict=True):
        cut = cut.withColumn(f"g{a}", F.explode(F.expr(f"sequence({a}0 div {w}, {a}1 div {w})")))
    held = bricks.filter(F.col("level") == level).select("key", "ix", "iy", "iz")
    # the cell that a brick's first voxel lies in; a brick may begin in the cell before the box
    held = held.withColumns({f"g{a}": F.expr(f"i{a} * {s} div {w}") for a, s, w in zip(AXES, side, width, strict=True)})
    within = " and ".join(f"i{a} * {s} <= {a}1 and i{a} * {s} + {s - 1} >= {a}0" for a, s in zip(AXES, side, strict=True))
    return held.join(cut, [f"g{a}" for a in AXES]).filter(within).select("box", "key", "ix", "iy", "iz").distinct()


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """``left`` (key, at) with the ``value`` of the last row of ``right`` (key, at, value) at or before it, null if there is none.

    Both sides meet in one sort by key and moment.  A key's rows are folded in order by a running
    ``last``; equal moments count as before.
    """
    both = left.select(key, at, F.lit(None).alias(value), F.lit(1).alias("asks")).unionByName(right.select(key, at, value, F.lit(0).alias("asks")))
    run = Window.partitionBy(key).orderBy(at, "asks").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(run)).filter("asks = 1").drop("asks")
