"""Perspective cameras: rays, samples, level of detail by distance, and images from resident bricks."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.grid import AXES, VolumeMeta, morton3
from ..storage import keep
from .fullframe import slots_side
from .raycast import ray_box


@dataclass(frozen=True)
class Camera:
    """Where the eye is, what it looks at, its vertical field of view in degrees and its screen."""

    eye: tuple[float, float, float]
    target: tuple[float, float, float]
    fov: float = 40.0
    width: int = 32
    height: int = 32

    @property
    def slope(self) -> float:
        return math.tan(math.radians(self.fov) / 2)

    @property
    def pixel_angle(self) -> float:
        """Width of a pixel at distance one."""
        return 2 * self.slope / self.height

    def basis(self) -> dict[str, tuple[float, float, float]]:
        """Forward, right and up vectors of length one."""
        forward = _unit(tuple(t - e for t, e in zip(self.target, self.eye, strict=True)))
        side = _cross(forward, (0.0, 1.0, 0.0))
        right = _unit(side if any(side) else (1.0, 0.0, 0.0))
        return {"forward": forward, "right": right, "up": _cross(right, forward)}


def _unit(v):
    n = math.sqrt(sum(a * a for a in v))
    return tuple(a / n for a in v)


def _cross(a, b):
    return (a[1] * b[2] - a[2] * b[1], a[2] * b[0] - a[0] * b[2], a[0] * b[1] - a[1] * b[0])


def turn(center, radius: float, frames: int, **screen) -> list[Camera]:
    """Cameras of one full turn around the y axis."""
    angles = (2 * math.pi * k / frames for k in range(frames))
    return [Camera((center[0] + radius * math.sin(t), center[1], center[2] + radius * math.cos(t)), tuple(map(float, center)), **screen) for t in angles]


def perspective_rays(spark: SparkSession, camera: Camera, vm: VolumeMeta) -> DataFrame:
    """One ray per pixel with its entry and exit in the volume box: px, py, ox..oz, dx..dz, enter, leave, hit.

    Rays are written once: filters on them would otherwise repeat their geometry all over the plan.
    """
    pixels = spark.range(camera.width * camera.height).select(F.expr(f"cast(id % {camera.width} as int)").alias("px"), F.expr(f"cast(id div {camera.width} as int)").alias("py"))
    aspect = camera.width / camera.height
    u = (F.lit(2.0) * (F.col("px") + F.lit(0.5)) / F.lit(float(camera.width)) - 1.0) * F.lit(camera.slope * aspect)
    v = (F.lit(1.0) - F.lit(2.0) * (F.col("py") + F.lit(0.5)) / F.lit(float(camera.height))) * F.lit(camera.slope)
    b = camera.basis()
    aimed = pixels.withColumns({"u": u, "v": v})
    aimed = aimed.withColumns({f"w{a}": F.lit(b["forward"][k]) + F.col("u") * b["right"][k] + F.col("v") * b["up"][k] for k, a in enumerate(AXES)})
    size = F.sqrt(F.col("wx") * F.col("wx") + F.col("wy") * F.col("wy") + F.col("wz") * F.col("wz"))
    aimed = aimed.withColumn("size", size)
    rays = aimed.select("px", "py", *(F.lit(float(camera.eye[k])).alias(f"o{a}") for k, a in enumerate(AXES)), *((F.col(f"w{a}") / F.col("size")).alias(f"d{a}") for a in AXES))
    return keep(ray_box(rays, vm.dims), "rays")


def sample_perspective(rays: DataFrame, vm: VolumeMeta, step: float) -> DataFrame:
    """Samples in the middle of every whole step between entry and exit: px, py, i, t and the voxel x, y, z."""
    some = rays.filter("hit").withColumn("n", F.floor((F.col("leave") - F.col("enter")) / F.lit(float(step))).cast("int")).filter("n > 0")
    some = some.withColumn("i", F.explode(F.expr("sequence(0, n - 1)")))
    some = some.withColumn("t", F.col("enter") + (F.col("i") + F.lit(0.5)) * F.lit(float(step)))
    place = [F.least(F.lit(d - 1), F.greatest(F.lit(0), F.floor(F.col(f"o{a}") + F.col(f"d{a}") * F.col("t")).cast("int"))).alias(a) for a, d in zip(AXES, vm.dims, strict=True)]
    return some.select("px", "py", "i", "t", *place)


def choose_level(samples: DataFrame, camera: Camera, vm: VolumeMeta) -> DataFrame:
    """Adds the level whose voxels are about as large as a pixel there, and the Morton key of its brick."""
    footprint = F.col("t") * F.lit(camera.pixel_angle)
    level = F.lit(0)
    for l in range(1, vm.top + 1):
        level = level + (footprint >= F.lit(float(1 << l))).cast("int")
    rows = samples.withColumn("level", level)
    place = [F.expr(f"shiftright({a}, level) div {m}") for a, m in zip(AXES, vm.brick, strict=True)]
    return rows.withColumn("key", morton3(*place, bits=vm.key_bits))


def resolve_at(samples: DataFrame, nodes: DataFrame, resident: DataFrame) -> DataFrame:
    """How far up (``up``: 0 own brick, 1 parent, 2 grand-parent, 3 the node's average) each sample's data is found.

    ``nodes`` (level, key, homog) is joined by key; ``resident`` (level, key) is sent to every task only if
    its size is that of a brick buffer.  Homogeneous nodes, and background nodes without a row, take the
    average and ask for nothing (``asks`` is false).
    """
    known = nodes.select("level", "key", F.col("homog").cast("int").alias("flat"))
    out = samples.join(known, ["level", "key"], "left")
    small = slots_side(resident) is not resident
    for up in range(3):
        slot = resident.select((F.col("level") - up).alias("level"), F.col("key").alias(f"k{up}"), F.lit(1).alias(f"r{up}"))
        slot = F.broadcast(slot) if small else slot
        at = F.shiftright("key", 3 * up) == F.col(f"k{up}")
        out = out.join(slot.withColumnRenamed("level", f"l{up}"), at & (F.col("level") == F.col(f"l{up}")), "left").drop(f"k{up}", f"l{up}")
    flat = F.coalesce("flat", F.lit(1)) == 1
    up = F.when(flat, 3).when(F.col("r0") == 1, 0).when(F.col("r1") == 1, 1).when(F.col("r2") == 1, 2).otherwise(3)
    kind = F.when(flat, "homogeneous").when(F.col("r0") == 1, "self").when(F.col("r1") == 1, "parent").when(F.col("r2") == 1, "grandparent").otherwise("average")
    return out.withColumns({"up": up, "asks": ~flat & F.col("r0").isNull(), "kind": kind}).drop("flat", "r0", "r1", "r2")


def image_of(resolved: DataFrame, mip: DataFrame, averages: DataFrame) -> DataFrame:
    """Maximum projection of resolved samples: px, py, c, v.

    ``mip`` (level, x, y, z, c, v) holds the voxels of all levels, ``averages`` (level, key, c, avg)
    the nodes' means.
    """
    stored = resolved.filter("up < 3").selectExpr("px", "py", "level + up as level", *(f"shiftright({a}, level + up) as {a}" for a in AXES))
    stored = stored.join(mip, ["level", *AXES]).select("px", "py", "c", "v")
    mean = resolved.filter("up = 3").select("px", "py", "level", "key").join(averages, ["level", "key"]).select("px", "py", "c", F.col("avg").alias("v"))
    return stored.unionByName(mean).groupBy("px", "py", "c").agg(F.max("v").alias("v"))


def image_error(image: DataFrame, truth: DataFrame, hi: int) -> DataFrame:
    """Per channel: pixels, mean and largest absolute difference, and peak signal-to-noise ratio (null: no difference)."""
    both = image.join(truth.withColumnRenamed("v", "w"), ["px", "py", "c"], "full")
    d = F.coalesce("v", F.lit(0)) - F.coalesce("w", F.lit(0))
    g = both.groupBy("c").agg(F.count("*").alias("pixels"), F.avg(F.abs(d)).alias("mae"), F.max(F.abs(d)).alias("worst"), F.avg((d * d).cast("double")).alias("mse"))
    return g.select("c", "pixels", "mae", "worst", F.when(F.col("mse") > 0, F.lit(10.0) * F.log10(F.lit(float(hi) * hi) / F.col("mse"))).alias("psnr"))
