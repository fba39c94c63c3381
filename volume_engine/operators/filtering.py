"""Trilinear filtering with and without brick borders, channel intermixing modes and a wavelet size measure."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.grid import AXES, VolumeMeta, coords
from .fullframe import halo_voxels
from .raycast import clear_before, clear_of_group


def corners(samples: DataFrame) -> DataFrame:
    """The eight cells around each sample (x, y, z and fractions fx, fy, fz in [0, 1)) with their weights: cx, cy, cz, w."""
    spark = samples.sparkSession
    eight = F.broadcast(spark.range(8).selectExpr(*(f"cast(shiftright(id, {k}) & 1 as int) as a{a}" for k, a in enumerate(AXES))))
    wide = samples.crossJoin(eight)  # eight rows
    weight = F.lit(1.0)
    for a in AXES:
        weight = weight * F.when(F.col(f"a{a}") == 1, F.col(f"f{a}")).otherwise(1.0 - F.col(f"f{a}"))
    return wide.withColumns({f"c{a}": F.col(a) + F.col(f"a{a}") for a in AXES} | {"w": weight}).filter("w > 0")


def trilinear(samples: DataFrame, voxels: DataFrame, vm: VolumeMeta, border: str = "global") -> DataFrame:
    """px, py, i, c, v of filtered samples; absent cells count as zero background.

    ``global`` looks cells up in the whole volume, ``clamp`` stays inside the sample's brick (no
    borders yet), ``overlap`` reads the brick enlarged by one voxel on each side.
    """
    wide = corners(samples)
    if border == "clamp":
        wide = wide.withColumns({f"c{a}": F.expr(f"least(c{a}, {a} div {m} * {m} + {m - 1})") for a, m in zip(AXES, vm.brick, strict=True)})
    cells = [F.col(a).alias(f"c{a}") for a in AXES]
    if border == "overlap":
        own = voxels.select(*(c.alias(k) for k, c in coords(0, vm).items()), *AXES, "c", "v")
        store = own.unionByName(halo_voxels(voxels, vm, 2)).select("ix", "iy", "iz", *cells, "c", "v")
        hit = wide.withColumns(coords(0, vm)).join(store, ["ix", "iy", "iz", "cx", "cy", "cz"])
    elif border in ("global", "clamp"):
        hit = wide.join(voxels.select(*cells, "c", "v"), ["cx", "cy", "cz"])
    else:
        raise ValueError(border)
    return hit.groupBy("px", "py", "i", "c").agg(F.sum(F.col("w") * F.col("v")).alias("v"))


def neighbour_fetches(samples: DataFrame, vm: VolumeMeta, voxels: DataFrame | None = None) -> DataFrame:
    """What filtering without borders costs: samples, samples that leave their brick and neighbour bricks they visit.

    With ``voxels``, bricks without any are background and not fetched.
    """
    wide = corners(samples).select("px", "py", "i", *(F.expr(f"{a} div {m}").alias(f"i{a}") for a, m in zip(AXES, vm.brick, strict=True)), *(F.expr(f"c{a} div {m}").alias(f"j{a}") for a, m in zip(AXES, vm.brick, strict=True)))
    away = F.expr("ix != jx or iy != jy or iz != jz")
    if voxels is not None:
        held = voxels.select(*(c.alias(f"j{k[1]}") for k, c in coords(0, vm).items())).distinct().withColumn("held", F.lit(True))
        wide = wide.join(held, ["jx", "jy", "jz"], "left")
        away = away & F.col("held")
    each = wide.groupBy("px", "py", "i").agg(F.count_distinct(F.when(away, F.struct("jx", "jy", "jz"))).alias("k"))
    return each.agg(F.count("*").alias("samples"), F.count_if(F.expr("k > 0")).alias("border_samples"), F.sum("k").alias("fetches"))


def _composite(rows: DataFrame, keys: list[str], order: list[str]) -> DataFrame:
    front = Window.partitionBy(*keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("t", clear_before(front))
    return rows.groupBy(*keys).agg(*(F.sum(F.col("t") * F.col("a") * F.col(k)).alias(k) for k in "rgb"), F.sum(F.col("t") * F.col("a")).alias("a"))


def intermix(shaded: DataFrame, mode: str) -> DataFrame:
    """Colour and opacity per pixel (px, py, r, g, b, a) of shaded samples (px, py, i, c, r, g, b, a).

    ``accumulation`` composites all channels of a sample one after the other, ``sample`` first mixes
    them by opacity, ``image`` composites each channel alone and adds the images up to full.
    """
    if mode == "accumulation":
        return _composite(shaded, ["px", "py"], ["i", "c"])
    if mode == "image":
        alone = _composite(shaded, ["px", "py", "c"], ["i"])
        return alone.groupBy("px", "py").agg(*(F.least(F.lit(1.0), F.sum(k)).alias(k) for k in "rgba"))
    if mode == "sample":
        total = F.sum("a")
        mixed = shaded.groupBy("px", "py", "i").agg(
            *(F.coalesce(F.sum(F.col("a") * F.col(k)) / F.nullif(total, F.lit(0.0)), F.lit(0.0)).alias(k) for k in "rgb"),
            (1 - clear_of_group()).alias("mixed"),
        )
        return _composite(mixed.withColumnRenamed("mixed", "a"), ["px", "py"], ["i"])
    raise ValueError(mode)


def haar_sizes(voxels: DataFrame, levels: int, voxel_bytes: int = 2) -> DataFrame:
    """Per level and channel: blocks, non-zero detail coefficients and their bytes of an integer Haar transform.

    A block of eight cells gives one sum, which is a cell of the next level, and seven signed sums;
    absent cells are zero and add nothing, so only stored cells are read.
    """
    cells, out = voxels.select(*AXES, "c", "v"), None
    for level in range(levels):
        sign = {k: " * ".join([f"(1 - 2 * ({a} & 1))" for j, a in enumerate(AXES) if k >> j & 1] or ["1"]) for k in range(8)}
        block = cells.groupBy(*(F.expr(f"{a} div 2").alias(f"h{a}") for a in AXES), "c").agg(*(F.sum(F.expr(f"v * {s}")).alias(f"s{k}") for k, s in sign.items()))
        details = " + ".join(f"cast(s{k} != 0 as int)" for k in range(1, 8))
        row = block.groupBy("c").agg(F.count("*").alias("blocks"), F.sum(F.expr(details)).alias("details")).withColumns({"level": F.lit(level), "bytes": F.col("details") * voxel_bytes})
        out = row if out is None else out.unionByName(row)
        cells = block.select(*(F.col(f"h{a}").alias(a) for a in AXES), "c", F.col("s0").alias("v"))
    return out
