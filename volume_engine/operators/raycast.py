"""Rays, samples, transfer functions and compositing as relations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.grid import VolumeMeta


def ortho_rays(spark: SparkSession, vm: VolumeMeta, width: int, height: int) -> DataFrame:
    """One ray per pixel along z: (px, py, x, y, t0, t1), through the middle of the pixel's footprint in the volume."""
    dx, dy, dz = vm.dims
    rays = spark.range(width * height).selectExpr(f"cast(id % {width} as int) px", f"cast(id div {width} as int) py")
    return rays.selectExpr("px", "py", f"(2 * px + 1) * {dx} div {2 * width} x", f"(2 * py + 1) * {dy} div {2 * height} y", "0 t0", f"{dz} t1")


def sample_rays(rays: DataFrame, step: int = 1) -> DataFrame:
    """Samples at t0, t0 + step, ... below t1: (px, py, i, x, y, z)."""
    some = rays.filter("t0 < t1").withColumn("i", F.explode(F.expr(f"sequence(0, cast((t1 - t0 - 1) div {step} as int))")))
    return some.selectExpr("px", "py", "i", "x", "y", f"cast(t0 + i * {step} as bigint) z")


def clip_rays(rays: DataFrame, near: int, far: int) -> DataFrame:
    """Rays limited by two clipping planes across z."""
    return rays.withColumns({"t0": F.greatest("t0", F.lit(near)), "t1": F.least("t1", F.lit(far))})


def ray_box(rays: DataFrame, dims) -> DataFrame:
    """Slab test of rays (ox..oz, dx..dz) with the volume box: enter, leave and hit."""
    lo, hi = [], []
    for a, d in zip("xyz", dims, strict=True):
        t = [f"({e} - o{a}) / d{a}" for e in ("0.0", f"{d}.0")]
        lo.append(f"if(d{a} = 0, if(o{a} between 0 and {d}, double('-1e30'), double('1e30')), least({t[0]}, {t[1]}))")
        hi.append(f"if(d{a} = 0, if(o{a} between 0 and {d}, double('1e30'), double('-1e30')), greatest({t[0]}, {t[1]}))")
    return rays.withColumns({"enter": F.expr(f"greatest({', '.join(lo)}, 0.0)"), "leave": F.expr(f"least({', '.join(hi)})")}).withColumn("hit", F.col("enter") < F.col("leave"))


def optimal_level(depth: Column, pixel_angle: float, top: int) -> Column:
    """Level whose voxels project to about a pixel at that distance from the camera."""
    return F.greatest(F.lit(0), F.least(F.lit(top), F.floor(F.log2(F.greatest(depth * pixel_angle, F.lit(1.0)))).cast("int")))


#: channel colours of the three-channel scenes and the opacity at full intensity
COLOURS = {0: (1.0, 0.0, 0.0), 1: (0.0, 1.0, 0.0), 2: (0.0, 0.0, 1.0)}
FULL_OPACITY = 0.5


def transfer(df: DataFrame, hi: int, colours=None) -> DataFrame:
    """Adds r, g, b, a: opacity rises linearly with intensity, the colour is the channel's."""
    colours = COLOURS if colours is None else colours
    out = {"a": F.col("v") * F.lit(FULL_OPACITY / hi)}
    for k, name in enumerate("rgb"):
        value = F.lit(0.0)
        for c, rgb in colours.items():
            value = F.when(F.col("c") == c, rgb[k]).otherwise(value)
        out[name] = value
    return df.withColumns(out)


def transfer_table(df: DataFrame, segments: list[tuple]) -> DataFrame:
    """Adds r, g, b, a by a table of linear segments (c, lo, hi, r0, g0, b0, a0, r1, g1, b1, a1); intensities outside all of them are dropped.

    The table is literals of the plan, found by a range join against a broadcast side.
    """
    names = [f"{k}{e}" for e in (0, 1) for k in "rgba"]
    table = df.sparkSession.createDataFrame([(int(s[0]), *(float(x) for x in s[1:])) for s in segments], "tc int, lo double, hi double, " + ", ".join(f"{n} double" for n in names))
    wide = df.join(F.broadcast(table), (F.col("c") == F.col("tc")) & (F.col("v") >= F.col("lo")) & (F.col("v") < F.col("hi")))
    at = (F.col("v") - F.col("lo")) / (F.col("hi") - F.col("lo"))
    return wide.select(*df.columns, *((F.col(f"{k}0") + at * (F.col(f"{k}1") - F.col(f"{k}0"))).alias(k) for k in "rgba"))


def dvr_wavefront(slabs: list, rays: DataFrame, alpha_stop: float, keep) -> tuple[DataFrame, list[tuple[int, int]]]:
    """Front-to-back compositing slab by slab; rays that have reached ``alpha_stop`` fetch nothing of later slabs.

    ``slabs`` are functions that give the shaded samples (px, py, i, c, r, g, b, a) of some rays (px, py)
    in one depth range each, front to back.  Returns the image as of ``dvr_window(..., alpha_stop)`` and, per
    slab, the rays still going and the samples fetched for them.
    """
    state = keep(rays.select("px", "py").distinct().select("px", "py", *(F.lit(0.0).alias(k) for k in "rgba"), F.lit(0).cast("long").alias("samples")))
    spent = []
    for slab in slabs:
        going = state.filter(F.col("a") < alpha_stop).select("px", "py", F.col("a").alias("before"))
        rows = keep(slab(going.select("px", "py")))
        spent.append((going.count(), rows.count()))
        front = Window.partitionBy("px", "py").orderBy("i", "c").rowsBetween(Window.unboundedPreceding, -1)
        rows = rows.join(going, ["px", "py"]).withColumn("t", (1 - F.col("before")) * clear_before(front)).filter(1 - F.col("t") < alpha_stop)
        part = rows.groupBy("px", "py").agg(*(F.sum(F.col("t") * F.col("a") * F.col(k)).alias(f"p{k}") for k in "rgb"), F.sum(F.col("t") * F.col("a")).alias("pa"), F.count("*").alias("pn"))
        moved = state.join(part, ["px", "py"], "left")
        state = keep(moved.select("px", "py", *((F.col(k) + F.coalesce(f"p{k}", F.lit(0.0))).alias(k) for k in "rgba"), (F.col("samples") + F.coalesce("pn", F.lit(0))).alias("samples")))
    return state, spent


def heat(v: Column, hi: int) -> tuple[Column, Column, Column]:
    """Piecewise linear heat map: black, red, yellow, white."""
    t = v / F.lit(float(hi)) * 3
    return tuple(F.greatest(F.lit(0.0), F.least(F.lit(1.0), t - k)) for k in range(3))


def fetch(samples: DataFrame, voxels: DataFrame) -> DataFrame:
    """Intensity of every sample and channel that is not background (nearest voxel)."""
    return samples.join(voxels, ["x", "y", "z"]).select("px", "py", "i", "c", "v")


def mip_image(fetched: DataFrame) -> DataFrame:
    """Maximum intensity per pixel and channel."""
    return fetched.groupBy("px", "py", "c").agg(F.max("v").alias("v"))


def _ln_clear(a: Column) -> Column:
    """Logarithm of a sample's transparency; an opaque one counts in ``_opaque`` instead."""
    return F.when(a < 1, F.log(1 - a)).otherwise(F.lit(0.0))


def _opaque(a: Column) -> Column:
    return F.when(a >= 1, 1).otherwise(0)


def clear_before(front, a: Column | None = None) -> Column:
    """Transparency of the rows of a window: the product of 1 - a, nothing if one of them is opaque."""
    a = F.col("a") if a is None else a
    blocked = F.coalesce(F.max(_opaque(a)).over(front), F.lit(0))
    return F.when(blocked == 1, 0.0).otherwise(F.exp(F.coalesce(F.sum(_ln_clear(a)).over(front), F.lit(0.0))))


def clear_of_group(a: Column | None = None) -> Column:
    """The same as an aggregate over a group."""
    a = F.col("a") if a is None else a
    return F.when(F.max(_opaque(a)) == 1, 0.0).otherwise(F.exp(F.sum(_ln_clear(a))))


def dvr_window(shaded: DataFrame, alpha_stop: float | None = None) -> DataFrame:
    """Front-to-back compositing over (i, c): transparency in front of a sample is a running product (of logarithms)."""
    front = Window.partitionBy("px", "py").orderBy("i", "c").rowsBetween(Window.unboundedPreceding, -1)
    rows = shaded.withColumn("t", clear_before(front))
    if alpha_stop is not None:
        rows = rows.filter(1 - F.col("t") < alpha_stop)
    return rows.groupBy("px", "py").agg(*(F.sum(F.col("t") * F.col("a") * F.col(k)).alias(k) for k in "rgb"), F.sum(F.col("t") * F.col("a")).alias("a"), F.count("*").alias("samples"))


def dvr_fold(shaded: DataFrame) -> DataFrame:
    """The same by an ordered fold over each ray's array of samples."""
    rays = shaded.groupBy("px", "py").agg(F.array_sort(F.collect_list(F.struct("i", "c", "r", "g", "b", "a"))).alias("s"))
    start = "named_struct('r', 0D, 'g', 0D, 'b', 0D, 'a', 0D)"
    step = "(p, q) -> named_struct(" + ", ".join(f"'{k}', p.{k} + (1 - p.a) * q.a * q.{k}" for k in "rgb") + ", 'a', p.a + (1 - p.a) * q.a)"
    return rays.withColumn("o", F.expr(f"aggregate(s, {start}, {step})")).select("px", "py", "o.r", "o.g", "o.b", "o.a", F.size("s").cast("long").alias("samples"))


def dvr_segments(shaded: DataFrame, length: int) -> DataFrame:
    """The same by runs of ``length`` samples: each run is composited alone, then the runs in order."""
    runs = shaded.withColumn("run", F.expr(f"i div {length}"))
    front = Window.partitionBy("px", "py", "run").orderBy("i", "c").rowsBetween(Window.unboundedPreceding, -1)
    runs = runs.withColumn("t", clear_before(front))
    part = runs.groupBy("px", "py", "run").agg(*(F.sum(F.col("t") * F.col("a") * F.col(k)).alias(k) for k in "rgb"), (1 - clear_of_group()).alias("a"), F.count("*").alias("n"))
    before = Window.partitionBy("px", "py").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)
    part = part.withColumn("t", clear_before(before))
    return part.groupBy("px", "py").agg(*(F.sum(F.col("t") * F.col(k)).alias(k) for k in "rgb"), F.sum(F.col("t") * F.col("a")).alias("a"), F.sum("n").alias("samples"))


def shift_channel(voxels: DataFrame, channel: int, shift=(0, 0, 0)) -> DataFrame:
    """On-the-fly channel correction by an integer translation, as a change of coordinates."""
    moved = {a: F.when(F.col("c") == channel, F.col(a) + s).otherwise(F.col(a)) for a, s in zip("xyz", shift, strict=True)}
    return voxels.withColumns(moved)


def transform_samples(samples: DataFrame, matrices: dict[int, list[list[float]]]) -> DataFrame:
    """Samples per channel with that channel's 3 x 4 matrix applied and rounded to voxels."""
    spark = samples.sparkSession
    rows = [(c, *(float(v) for row in m for v in row)) for c, m in matrices.items()]
    names = [f"m{i}{j}" for i in range(3) for j in range(4)]
    table = F.broadcast(spark.createDataFrame(rows, "c int, " + ", ".join(f"{n} double" for n in names)))
    wide = samples.join(table)
    out = {a: F.floor(F.expr(f"m{i}0 * (x + 0.5) + m{i}1 * (y + 0.5) + m{i}2 * (z + 0.5) + m{i}3")).alias(a) for i, a in enumerate("xyz")}
    return wide.select("px", "py", "i", "c", *out.values())
