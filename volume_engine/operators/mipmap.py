"""The mipmap and its brick statistics over sparse voxels."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.grid import AXES, VolumeMeta, coords, inside, morton3


def shard_height(vm: VolumeMeta, most: int = 4096) -> int:
    """Lowest level with at most ``most`` bricks: its bricks are the units that rows are partitioned by."""
    for level in range(vm.top + 1):
        if vm.bricks_at(level)[0] * vm.bricks_at(level)[1] * vm.bricks_at(level)[2] <= most:
            return level
    return vm.top


def sharded(voxels: DataFrame, vm: VolumeMeta) -> tuple[DataFrame, int]:
    """Voxels partitioned once by their brick at the shard level; grouping by (shard, ...) needs no further exchange below it."""
    height = shard_height(vm)
    place = [F.expr(f"{a} div {m << height}") for a, m in zip(AXES, vm.brick, strict=True)]
    return voxels.withColumn("shard", morton3(*place, bits=vm.key_bits)).repartition("shard"), height


def half_sample(mip: DataFrame, vm: VolumeMeta, level: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """One level up: the mean over the children that lie in the volume; absent children hold the background."""
    cells = mip.select(*keys, *(F.expr(f"{a} div 2").cast("int").alias(a) for a in AXES), "c", "v")
    grouped = cells.groupBy(*keys, *AXES, "c").agg(F.sum("v").alias("s"), F.count("*").alias("cnt"))
    dims = vm.at_level(level)
    n = reduce(lambda p, q: p * q, (inside(F.col(a), d) for a, d in zip(AXES, dims, strict=True)))
    mean = grouped.withColumn("n", n)
    return mean.select(*keys, *AXES, "c", F.expr(f"(s + {vm.background} * (n - cnt)) div n").alias("v"))


def build_mipmap(voxels: DataFrame, vm: VolumeMeta) -> list[DataFrame]:
    """Levels 0 to top as (x, y, z, c, v)."""
    rows, height = sharded(voxels.select(*AXES, "c", "v"), vm)
    levels = [rows]
    for level in range(vm.top):
        below = levels[-1] if level < height else levels[-1].drop("shard")
        levels.append(half_sample(below, vm, level, ("shard",) if level < height else ()))
    return [m.drop("shard") for m in levels]


def mipmap_rows(voxels: DataFrame, vm: VolumeMeta) -> DataFrame:
    """All levels in one relation with a ``level`` column."""
    return reduce(DataFrame.unionByName, (m.withColumn("level", F.lit(l)) for l, m in enumerate(build_mipmap(voxels, vm))))


def valid_count(level: int, vm: VolumeMeta):
    """Voxels of brick (ix, iy, iz) that lie in the volume, in closed form."""
    return reduce(lambda p, q: p * q, (inside(F.col(f"i{a}"), d, m) for a, d, m in zip(AXES, vm.at_level(level), vm.brick, strict=True)))


def brick_stats(mip: DataFrame, vm: VolumeMeta, level: int) -> DataFrame:
    """Per brick and channel: valid voxels, minimum, maximum, sum and floored mean, absent voxels counted as background."""
    bg = vm.background
    rows = mip.select(*(c.alias(k) for k, c in coords(level, vm).items()), "c", "v")
    g = rows.groupBy("ix", "iy", "iz", "c").agg(F.min("v").alias("lo"), F.max("v").alias("hi"), F.sum("v").alias("s"), F.count("*").alias("cnt"))
    g = g.withColumn("n", valid_count(level, vm))
    return g.select(
        F.lit(level).alias("level"), "ix", "iy", "iz", "c", "n",
        F.expr(f"if(cnt < n, least(lo, {bg}), lo)").alias("bmin"), F.expr(f"if(cnt < n, greatest(hi, {bg}), hi)").alias("bmax"),
        F.expr(f"s + {bg} * (n - cnt)").alias("bsum"), F.expr(f"(s + {bg} * (n - cnt)) div n").alias("avg"),
    )


def pyramid_stats(voxels: DataFrame, vm: VolumeMeta) -> DataFrame:
    """Brick statistics of all levels plus subtree minimum and maximum (smin, smax), bottom-up."""
    out, below = [], None
    for level, mip in enumerate(build_mipmap(voxels, vm)):
        own = brick_stats(mip, vm, level)
        if below is None:
            own = own.withColumns({"smin": F.col("bmin"), "smax": F.col("bmax")})
        else:
            up = below.select(*(F.expr(f"i{a} div 2").alias(f"i{a}") for a in AXES), "c", "smin", "smax")
            up = up.groupBy("ix", "iy", "iz", "c").agg(F.min("smin").alias("kmin"), F.max("smax").alias("kmax"), F.count("*").alias("kids"))
            expected = reduce(lambda p, q: p * q, (inside(F.col(f"i{a}"), n) for a, n in zip(AXES, vm.bricks_at(level - 1), strict=True)))
            up = up.withColumn("missing", expected > F.col("kids"))
            own = own.join(up, ["ix", "iy", "iz", "c"])
            bg = vm.background
            own = own.withColumns({"smin": F.expr(f"least(bmin, kmin, if(missing, {bg}, kmin))"), "smax": F.expr(f"greatest(bmax, kmax, if(missing, {bg}, kmax))")}).drop("kmin", "kmax", "kids", "missing")
        out.append(own)
        below = own
    return reduce(DataFrame.unionByName, out)


def pack_bricks(mip: DataFrame, vm: VolumeMeta, level: int, layout: str = "interleaved") -> DataFrame:
    """Dense brick bodies: one array per brick, channels interleaved or planar; absent voxels hold the background."""
    mx, my, mz = vm.brick
    cells = mx * my * mz
    flat = f"((z % {mz}) * {my} + y % {my}) * {mx} + x % {mx}"
    offset = f"({flat}) * {vm.channels} + c" if layout == "interleaved" else f"c * {cells} + {flat}"
    rows = mip.select(*(c.alias(k) for k, c in coords(level, vm).items()), F.expr(f"cast({offset} as int)").alias("off"), "v")
    packed = rows.groupBy("ix", "iy", "iz").agg(F.map_from_entries(F.collect_list(F.struct("off", "v"))).alias("m"))
    body = f"transform(sequence(0, {cells * vm.channels - 1}), i -> coalesce(try_element_at(m, i), {vm.background}L))"
    return packed.select(F.lit(level).alias("level"), morton3(F.col("ix"), F.col("iy"), F.col("iz"), vm.key_bits).alias("key"), "ix", "iy", "iz", F.expr(body).alias("body"))


def unpack_bricks(bricks: DataFrame, vm: VolumeMeta) -> DataFrame:
    """Voxels in the volume of interleaved bodies."""
    mx, my, mz = vm.brick
    c = vm.channels
    rows = bricks.select("level", "ix", "iy", "iz", F.posexplode("body").alias("off", "v"))
    rows = rows.select("level", F.expr(f"ix * {mx} + off div {c} % {mx}").alias("x"), F.expr(f"iy * {my} + off div {c * mx} % {my}").alias("y"), F.expr(f"iz * {mz} + off div {c * mx * my}").alias("z"), F.expr(f"off % {c}").alias("c"), "v")
    far = [F.lit(None).cast("int")] * 3
    for l in range(vm.top + 1):
        far = [F.when(F.col("level") == l, d).otherwise(f) for d, f in zip(vm.at_level(l), far, strict=True)]
    return rows.filter((F.col("x") < far[0]) & (F.col("y") < far[1]) & (F.col("z") < far[2]))
