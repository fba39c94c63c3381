"""The ray-casting loop over a brick pool: node at the wanted level, residency, brick or substitute, and passes with uploads.

Samples (px, py, i, level, key, x, y, z) come from a camera.  A homogeneous node gives its average;
a resident brick its voxel; a missing brick is asked for and, by mode, replaced by the node's average
(``basic``, ``average``), by the parent's or grand-parent's brick if one is resident (``full_frame``), or
by nothing (``direct`` reads every brick, as with a buffer for the whole pool).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.codec import REQUESTED, USED
from ..functions.grid import AXES, VolumeMeta
from .camera import resolve_at
from .paging import plan_uploads
from .raycast import dvr_window, mip_image

MODES = ("full_frame", "basic", "average", "direct")


def resolve(samples: DataFrame, nodes: DataFrame, resident: DataFrame, mode: str = "full_frame") -> DataFrame:
    """Samples with ``kind``, ``up`` (levels above the wanted one, 3: average) and ``asks``."""
    if mode not in MODES:
        raise ValueError(mode)
    found = resolve_at(samples, nodes, resident)
    if mode == "full_frame":
        return found
    flat, own = F.col("kind") == "homogeneous", F.col("kind") == "self"
    keep = {"basic": own, "average": F.lit(False), "direct": ~flat}[mode]
    kind = F.when(flat, "homogeneous").when(keep, "self").otherwise("average")
    return found.withColumns({"kind": kind, "up": F.when(~flat & keep, 0).otherwise(3), "asks": F.lit(False) if mode in ("average", "direct") else F.col("asks")})


def offset(vm: VolumeMeta, level: Column) -> Column:
    """Place of a sample's voxel in the body of its brick at a level (channel 0)."""
    mx, my, mz = vm.brick
    at = {a: F.expr(f"shiftright({a}, at)") for a in AXES}
    return ((at["z"] % mz * my + at["y"] % my) * mx + at["x"] % mx) * vm.channels


def fetch(resolved: DataFrame, bricks: DataFrame, averages: DataFrame, vm: VolumeMeta) -> DataFrame:
    """Intensity of every resolved sample and inserted channel: px, py, i, c, v.

    Samples travel to the bricks by (level, key); a brick that no sample needs is not opened.
    """
    stored = resolved.filter("up < 3").withColumn("at", F.col("level") + F.col("up"))
    stored = stored.select("px", "py", "i", "at", F.expr("shiftright(key, 3 * up)").alias("key"), offset(vm, F.col("at")).cast("int").alias("off"))
    opened = stored.join(bricks.select(F.col("level").alias("at"), "key", "body"), ["at", "key"])
    opened = opened.select("px", "py", "i", F.posexplode(F.expr(f"slice(body, off + 1, {vm.channels})")).alias("c", "v")).filter("v is not null")
    mean = resolved.filter("up = 3").select("px", "py", "i", "level", "key").join(averages.select("level", "key", "c", F.col("avg").alias("v")), ["level", "key"])
    return opened.select("px", "py", "i", "c", F.col("v").cast("long").alias("v")).unionByName(mean.select("px", "py", "i", F.col("c").cast("int").alias("c"), F.col("v").cast("long").alias("v")))


def waiting(fetched: DataFrame, resolved: DataFrame) -> DataFrame:
    """Fetched intensities with the brick (``key``) that each sample waits for, null where the node is homogeneous.

    A sample that meets nothing but background still needs its brick: it counts as an intensity of 0.
    """
    need = resolved.filter("up < 3").select("px", "py", "i", (F.expr("shiftright(key, 3 * up)") * 32 + F.col("level") + F.col("up")).alias("key"))
    rows = fetched.join(need, ["px", "py", "i"], "full")
    return rows.select("px", "py", "i", F.coalesce("c", F.lit(0)).alias("c"), F.coalesce("v", F.lit(0)).alias("v"), "key")


def image(fetched: DataFrame, projection: str, shade: Callable[[DataFrame], DataFrame], alpha_stop: float | None = None) -> DataFrame:
    """``mip``: px, py, c, v; ``dvr``: px, py, r, g, b, a, samples with ``shade`` as the transfer function."""
    if projection == "mip":
        return mip_image(fetched)
    if projection == "dvr":
        return dvr_window(shade(fetched), alpha_stop)
    raise ValueError(projection)


def used(resolved: DataFrame) -> DataFrame:
    """Distinct bricks (level, key) that gave an intensity."""
    return resolved.filter("up < 3").select((F.col("level") + F.col("up")).alias("level"), F.expr("shiftright(key, 3 * up)").alias("key")).distinct()


def requested(resolved: DataFrame, top: int, ancestors: int = 2) -> DataFrame:
    """Bricks asked for (level, key) with the samples that wait: the missing one and, up to the root, its ancestors."""
    asking = resolved.filter("asks").groupBy("level", "key").agg(F.count("*").alias("n"))
    wide = asking.select("level", "key", "n", F.explode(F.sequence(F.lit(0), F.lit(ancestors))).alias("j")).filter(f"level + j <= {top}")
    return wide.groupBy((F.col("level") + F.col("j")).alias("level"), F.expr("shiftright(key, 3 * j)").alias("key")).agg(F.sum("n").alias("waiting"))


def flags(resolved: DataFrame, top: int, ancestors: int = 2) -> DataFrame:
    """Flag entries (level, key, flags) of a pass: bricks used and bricks asked for."""
    both = used(resolved).withColumn("flag", F.lit(USED)).unionByName(requested(resolved, top, ancestors).select("level", "key", F.lit(REQUESTED).alias("flag")))
    return both.groupBy("level", "key").agg(F.bit_or("flag").alias("flags"))


def evaluate_flags(entries: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The used and the requested set of a flag buffer."""
    one = F.col("flags")
    return entries.filter(one.bitwiseAND(USED) != 0).select("level", "key"), entries.filter(one.bitwiseAND(REQUESTED) != 0).select("level", "key")


def candidates(resolved: DataFrame, nodes: DataFrame, resident: DataFrame, top: int, ancestors: int = 2) -> DataFrame:
    """What the upload planner chooses from: level, key, used, resident, waiting and seq; homogeneous nodes have no brick to send."""
    asked = requested(resolved, top, ancestors)
    stored = nodes.filter("not homog").select("level", "key")
    asked = asked.join(stored, ["level", "key"], "left_semi")
    held = resident.select("level", "key", F.lit(1).alias("resident"))
    rows = asked.join(held, ["level", "key"], "full").join(used(resolved).withColumn("u", F.lit(1)), ["level", "key"], "left")
    wanted = F.col("u").isNotNull() | F.col("waiting").isNotNull()
    return rows.select("level", "key", wanted.cast("int").alias("used"), F.coalesce("resident", F.lit(0)).alias("resident"), F.coalesce("waiting", F.lit(0)).alias("waiting"), F.xxhash64("level", "key").alias("seq"))


def run_passes(samples: DataFrame, nodes: DataFrame, top: int, slots: int, keep, mode: str = "full_frame", policy: str = "coarse_first", most: int = 16, start: DataFrame | None = None) -> tuple[DataFrame, list[dict]]:
    """Passes with uploads between them until nothing more can be loaded or ``most`` is reached.

    Returns the last pass's resolved samples and, per pass, samples by kind, bricks asked for, uploaded
    and dropped, and slots taken.  The buffer starts with ``start`` or the root brick alone.
    """
    ancestors = 2 if mode == "full_frame" else 0
    resident = keep(nodes.filter((F.col("level") == top) & ~F.col("homog")).select("level", "key") if start is None else start.select("level", "key"))
    out = []
    while True:
        resolved = keep(resolve(samples, nodes, resident, mode))
        kinds = {r["kind"]: r["count"] for r in resolved.groupBy("kind").count().collect()}
        asked = candidates(resolved, nodes, resident, top, ancestors)
        plan = plan_uploads(asked, slots, policy).select("level", "key") if policy != "fifo" else _fill(asked, resident, slots)
        following = keep(plan)
        gone = resident.join(following, ["level", "key"], "left_anti").count()
        new = following.join(resident, ["level", "key"], "left_anti").count()
        out.append({"kinds": kinds, "requests": asked.filter("waiting > 0 and resident = 0").count(), "uploads": new, "evictions": gone, "slots": following.count()})
        if not new or len(out) >= most:
            return resolved, out
        resident = following


def _fill(asked: DataFrame, resident: DataFrame, slots: int) -> DataFrame:
    """First come, first served: residents stay, requests fill the slots that are left."""
    free = max(0, slots - resident.count())
    return resident.select("level", "key").unionByName(plan_uploads(asked, free, "fifo").select("level", "key")) if free else resident.select("level", "key")


def tile(samples: DataFrame, width: int, tiles: list[tuple[int, int]] | None = None) -> DataFrame:
    """Samples with their screen tile (tx, ty), of all tiles or some."""
    rows = samples.withColumns({"tx": F.expr(f"px div {width}"), "ty": F.expr(f"py div {width}")})
    if tiles is None:
        return rows
    return rows.filter(" or ".join(f"(tx = {a} and ty = {b})" for a, b in tiles) or "false")


def clipped(samples: DataFrame, planes: list[tuple[float, float, float, float]]) -> DataFrame:
    """Samples on the positive side of every clipping plane a x + b y + c z + d >= 0 (voxel centres)."""
    for a, b, c, d in planes:
        samples = samples.filter(F.lit(float(a)) * (F.col("x") + 0.5) + F.lit(float(b)) * (F.col("y") + 0.5) + F.lit(float(c)) * (F.col("z") + 0.5) + F.lit(float(d)) >= 0)
    return samples
