"""Approximation from resident bricks, requests, refinement passes and borders."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.grid import AXES, VolumeMeta
from .raycast import dvr_window


#: Most slots whose list is sent to every task; a longer one is joined by shuffle.
MOST_SLOTS = 1 << 16


def slots_side(resident: DataFrame) -> DataFrame:
    """``resident`` with a broadcast hint if it holds no more rows than a brick buffer has slots."""
    return F.broadcast(resident) if resident.limit(MOST_SLOTS + 1).count() <= MOST_SLOTS else resident


def resolve_source(needed: DataFrame, resident: DataFrame) -> DataFrame:
    """Where each needed level-0 brick (key, homog) is taken from: homogeneous, itself, parent, grand-parent or average.

    ``resident`` (level, key) is sent to every task only if its size is that of a brick buffer.
    """
    small = slots_side(resident) is not resident
    out = needed
    for l in range(3):
        side = resident.filter(F.col("level") == l).select(F.col("key").alias(f"k{l}"), F.lit(1).alias(f"r{l}"))
        out = out.join(F.broadcast(side) if small else side, F.shiftright("key", 3 * l) == F.col(f"k{l}"), "left").drop(f"k{l}")
    kind = F.when(F.col("homog") == 1, "homogeneous").when(F.col("r0") == 1, "self").when(F.col("r1") == 1, "parent").when(F.col("r2") == 1, "grandparent").otherwise("average")
    return out.withColumn("kind", kind).drop("r0", "r1", "r2")


def requests(resolved: DataFrame, levels: int = 3) -> DataFrame:
    """Distinct bricks asked for: every missing brick with its parent and grand-parent, and how many wait."""
    missing = resolved.filter("kind in ('parent', 'grandparent', 'average')").select("key", F.explode(F.sequence(F.lit(0), F.lit(levels - 1))).alias("level"))
    return missing.groupBy("level", F.expr("shiftright(key, 3 * level)").alias("key")).agg(F.count("*").alias("waiting"))


def halt_points(samples: DataFrame, resident: DataFrame) -> DataFrame:
    """Per ray, the first sample whose brick is neither resident nor homogeneous (null: the ray is done).

    ``samples`` (px, py, i, key) lists the samples; those without a key need no brick.
    """
    here = samples.join(slots_side(resident.select("key", F.lit(1).alias("here"))), "key", "left")
    return here.groupBy("px", "py").agg(F.min(F.when(F.col("key").isNotNull() & F.col("here").isNull(), F.col("i"))).alias("halt"))


def refine(samples: DataFrame, slots: int, keep, most_passes: int = 1000) -> tuple[int, int]:
    """Passes and uploads until no ray waits, each pass loading the ``slots`` bricks most rays wait for.

    Every pass is one job and one count on the driver; ``keep`` cuts the lineage of the ray states.
    """
    state = keep(samples.select("px", "py").distinct().withColumn("at", F.lit(-1)))
    passes = uploads = 0
    resident = samples.select("key").filter("false")
    while passes < most_passes:
        active = samples.join(state, ["px", "py"]).filter("i >= at")
        halts = halt_points(active, resident).filter("halt is not null")
        wanted = active.join(halts, ["px", "py"]).filter("i = halt").groupBy("key").agg(F.count("*").alias("rays"))
        resident = keep(wanted.orderBy(F.desc("rays"), "key").limit(slots).select("key"))
        loaded = resident.count()
        if not loaded:
            return passes, uploads
        passes, uploads = passes + 1, uploads + loaded
        state = keep(halts.withColumnRenamed("halt", "at"))
    raise RuntimeError("refinement did not end")


def refine_image(shaded: DataFrame, slots: int, keep, most_passes: int = 1000) -> tuple[DataFrame, int, int]:
    """The finished image (px, py, r, g, b, a, samples) of refinement, with its passes and uploads.

    ``shaded`` (px, py, i, c, key, r, g, b, a) lists the samples; those without a key need no brick.  A ray keeps its place and
    the colour and opacity up to there; each pass takes it on to its next missing brick, then all ``slots``
    are given to the bricks most rays wait for.  The image is handed out when no ray waits any more.
    """
    shaded = keep(shaded.select("px", "py", "i", "c", "key", *"rgba"))
    state = keep(shaded.select("px", "py").distinct().select("px", "py", F.lit(-1).alias("at"), *(F.lit(0.0).alias(k) for k in "rgba"), F.lit(0).cast("long").alias("samples")))
    passes = uploads = 0
    resident = shaded.select("key").filter("false")
    while passes < most_passes:
        ahead = shaded.join(state.filter("at is not null").select("px", "py", "at"), ["px", "py"]).filter("i >= at").drop("at")
        halts = keep(halt_points(ahead.select("px", "py", "i", "key"), resident))
        part = dvr_window(ahead.join(halts, ["px", "py"]).filter("halt is null or i < halt"))
        part = part.select("px", "py", *(F.col(k).alias(f"part_{k}") for k in (*"rgba", "samples")))
        moved = state.join(halts, ["px", "py"], "left").join(part, ["px", "py"], "left")
        behind = {k: F.col(k) + (1 - F.col("a")) * F.coalesce(f"part_{k}", F.lit(0.0)) for k in "rgba"}
        state = keep(moved.select("px", "py", F.col("halt").alias("at"), *(c.alias(k) for k, c in behind.items()), (F.col("samples") + F.coalesce("part_samples", F.lit(0))).alias("samples")))
        waiting = ahead.join(halts, ["px", "py"]).filter("i = halt").select("px", "py", "key").distinct()
        wanted = waiting.groupBy("key").agg(F.count("*").alias("rays"))
        resident = keep(wanted.orderBy(F.desc("rays"), "key").limit(slots).select("key"))
        loaded = resident.count()
        if not loaded:
            return state.drop("at"), passes, uploads
        passes, uploads = passes + 1, uploads + loaded
    raise RuntimeError("refinement did not end")


def refine_mip(fetched: DataFrame, slots: int, keep, most_passes: int = 1000) -> tuple[DataFrame, int, int]:
    """The finished maximum projection (px, py, c, v) of refinement, with its passes and uploads.

    ``fetched`` (px, py, i, c, key, v) as for ``refine_image``; a ray keeps its place and its greatest
    intensities so far.  No ray ends early, so every brick is loaded that a sample needs.
    """
    fetched = keep(fetched.select("px", "py", "i", "c", "key", "v"))
    places = keep(fetched.select("px", "py").distinct().withColumn("at", F.lit(-1)))
    best = fetched.select("px", "py", "c", "v").limit(0)
    passes = uploads = 0
    resident = fetched.select("key").filter("false")
    while passes < most_passes:
        ahead = fetched.join(places.filter("at is not null"), ["px", "py"]).filter("i >= at").drop("at")
        halts = keep(halt_points(ahead.select("px", "py", "i", "key"), resident))
        part = ahead.join(halts, ["px", "py"]).filter("halt is null or i < halt").select("px", "py", "c", "v")
        best = keep(best.unionByName(part).groupBy("px", "py", "c").agg(F.max("v").alias("v")))
        waiting = ahead.join(halts, ["px", "py"]).filter("i = halt").select("px", "py", "key").distinct()
        resident = keep(waiting.groupBy("key").agg(F.count("*").alias("rays")).orderBy(F.desc("rays"), "key").limit(slots).select("key"))
        loaded = resident.count()
        if not loaded:
            return best, passes, uploads
        passes, uploads = passes + 1, uploads + loaded
        places = halts.withColumnRenamed("halt", "at")
    raise RuntimeError("refinement did not end")


def halo_voxels(voxels: DataFrame, vm: VolumeMeta, sides: int = 2) -> DataFrame:
    """Voxels that bricks hold beyond their own: one row per (brick, border voxel), one or two sides."""
    steps = [-1, 0, 1] if sides == 2 else [-1, 0]
    wide = voxels.crossJoin(F.broadcast(voxels.sparkSession.createDataFrame([(a, b, c) for a in steps for b in steps for c in steps if (a, b, c) != (0, 0, 0)], "sx int, sy int, sz int")))
    for a, m, d in zip(AXES, vm.brick, vm.dims, strict=True):
        wide = wide.filter(f"{a} + s{a} >= 0 and {a} + s{a} < {-(-d // m) * m}").withColumn(f"i{a}", F.expr(f"({a} + s{a}) div {m}"))
    outside = " or ".join(f"i{a} != {a} div {m}" for a, m in zip(AXES, vm.brick, strict=True))
    return wide.filter(outside).select("ix", "iy", "iz", *AXES, "c", "v").distinct()
