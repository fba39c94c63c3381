"""The experiment workloads: building, turning, refining, memory regimes, live scans and builders side by side.

Each function returns plain dictionaries of measures for a volume of the given tables.  Times are
wall clock of the whole call, writes included; counts come from the library's own relations.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import storage
from .operators import camera as cam
from .operators import fullframe, ingest, octree, paging, raycast, render
from .operators.pool import BrickPool
from .sources import raw_stack
from .sources.catalog import volume
from .streaming import stream_ingest

PERCENT = 5.0


def timed(work):
    begin = time.perf_counter()
    out = work()
    return out, round(time.perf_counter() - begin, 3)


def run_build(spark: SparkSession, sf_dir: str, name: str, parallel: str = "shards") -> dict:
    """Construction time and what the pool holds, homogeneous bricks under a threshold of five percent of the range."""
    opened = volume(spark, sf_dir, name, fresh=True)
    vm = opened.vm
    voxels = storage.keep(opened.voxels, "voxels")
    pool, seconds = timed(lambda: ingest.build(voxels, vm, parallel))
    nodes = octree.nodes_of_bricks(pool.bricks(), vm, vm.threshold(PERCENT, "percent"))
    held = octree.collapse(nodes, vm)
    all_bricks, homogeneous = nodes.agg(F.count("*"), F.count_if("homog")).first()
    kept = held.filter("has_brick").count()
    body = vm.brick[0] * vm.brick[1] * vm.brick[2] * vm.channels * vm.voxel_bytes
    data = vm.dims[0] * vm.dims[1] * vm.dims[2] * vm.channels * vm.voxel_bytes
    if parallel == "shards":
        opened._pool = pool
    return {
        "build_s": seconds, "bricks": all_bricks, "bricks_per_s": round(all_bricks / seconds, 1), "data_mb": round(data / 1e6, 3), "data_mb_per_s": round(data / 1e6 / seconds, 2),
        "pool_mb": round(kept * body / 1e6, 3), "pool_over_data": round(kept * body / data, 3), "homogeneous": round(homogeneous / max(1, all_bricks), 3), "stored_mb": round(storage.bytes_of(spark, pool.path) / 1e6, 3),
    }


def view_samples(spark: SparkSession, vm, view: cam.Camera, step: float) -> DataFrame:
    return cam.choose_level(cam.sample_perspective(cam.perspective_rays(spark, view, vm), vm, step), view, vm)


def scene(spark: SparkSession, sf_dir: str, name: str):
    opened = volume(spark, sf_dir, name)
    nodes = storage.keep(opened.nodes(opened.vm.threshold(PERCENT, "percent")), "nodes")
    averages = storage.keep(opened.pool.stats().join(opened.pool.bricks().select("level", "ix", "iy", "iz", "key"), ["level", "ix", "iy", "iz"]).select("level", "key", "c", "avg"), "averages")
    return opened, nodes, averages


def cameras(vm, frames: int, pixels: int) -> list[cam.Camera]:
    center = tuple(d / 2 for d in vm.dims)
    return cam.turn(center, 1.6 * max(vm.dims), frames, width=pixels, height=pixels)


def run_rotation(spark: SparkSession, sf_dir: str, name: str, frames: int = 8, pixels: int = 32, slots: int = 256, projection: str = "dvr", step: float | None = None) -> dict:
    """Full-frame passes of a turn: the buffer goes from frame to frame; seconds a frame, uploads, sources and page loads."""
    opened, nodes, averages = scene(spark, sf_dir, name)
    vm, bricks = opened.vm, opened.pool.bricks()
    step = max(1.0, max(vm.dims) / 128) if step is None else step
    start, kinds, seconds, passes, loads = None, {}, [], [], 0
    in_ram: set[tuple[int, int]] = set()
    for view in cameras(vm, frames, pixels):
        def frame(view=view):
            nonlocal start
            samples = storage.keep(view_samples(spark, vm, view, step), "samples")
            resolved, done = render.run_passes(samples, nodes, vm.top, slots, storage.keep, most=1, start=start)
            render.image(render.fetch(resolved, bricks, averages, vm), projection, lambda f: raycast.transfer(f, vm.hi)).write.format("noop").mode("overwrite").save()
            start = storage.keep(paging.plan_uploads(render.candidates(resolved, nodes, start if start is not None else nodes.filter(F.col("level") == vm.top).select("level", "key"), vm.top), slots).select("level", "key"))
            return resolved, done

        (resolved, done), s = timed(frame)
        seconds.append(s)
        passes += done
        pages = {(r[0], r[1]) for r in start.select("level", F.shiftright("key", 6)).distinct().collect()}  # no more rows than slots
        loads += len(pages - in_ram)
        in_ram |= pages
        for k, n in done[-1]["kinds"].items():
            kinds[k] = kinds.get(k, 0) + n
    total = max(1, sum(kinds.values()))
    return {"frames": frames, "s_per_frame": round(sum(seconds) / frames, 3), "requests": sum(p["requests"] for p in passes), "uploads": sum(p["uploads"] for p in passes), "page_loads": loads, "sources": {k: round(n / total, 4) for k, n in sorted(kinds.items())}}


def run_refinement(spark: SparkSession, sf_dir: str, name: str, slots: int = 64, pixels: int = 32, projection: str = "dvr", cap_pages: int | None = None) -> dict:
    """Refinement of one view to its end: seconds, passes, uploads and, with a cap on pages, page switches."""
    opened, nodes, averages = scene(spark, sf_dir, name)
    vm = opened.vm
    view = cameras(vm, 4, pixels)[0]
    samples = view_samples(spark, vm, view, max(1.0, max(vm.dims) / 128))
    resolved = render.resolve(samples, nodes, nodes.select("level", "key").limit(0), "direct")
    need = storage.keep(resolved.filter("up = 0").select("px", "py", "i", "level", "key"), "needed")
    fetched = render.fetch(resolved, opened.pool.bricks(), averages, vm)
    fetched = render.waiting(fetched, resolved)
    work = (lambda: fullframe.refine_mip(fetched, slots, storage.keep)) if projection == "mip" else (lambda: fullframe.refine_image(raycast.transfer(fetched, vm.hi), slots, storage.keep))
    (_, passes, uploads), seconds = timed(work)
    out = {"refine_s": seconds, "passes": passes, "uploads": uploads, "needed": need.select("level", "key").distinct().count()}
    order = need.groupBy("level", "key").agg(F.min("i").alias("first")).withColumn("cache", F.lit(0).cast("long"))
    order = order.select("cache", (F.col("first") * (1 << 40) + F.col("key")).alias("seq"), "level", "key")
    trace = paging.page_trace(order).select("cache", "seq", "page", *(F.lit(False).alias(k) for k in ("write", "pin", "unpin")))
    out["page_switches"] = paging.simulate_lru(trace, cap_pages or 1 << 30).agg(F.count_if(F.expr("hit = 0"))).first()[0]
    return out


def run_live_scan(spark: SparkSession, sf_dir: str, slices: int = 24) -> dict:
    """A scan that streams in, a version and a preview per micro-batch: time to the first image against building all first."""
    opened = volume(spark, sf_dir, "scan")
    vm = opened.vm
    rays = raycast.ortho_rays(spark, vm, 16, 16)
    begin, firsts = time.perf_counter(), []

    def preview(version: int) -> None:
        early = pool.voxels(version, 0).join(F.broadcast(rays), ["x", "y"])
        if raycast.mip_image(early.select("px", "py", "c", "v")).limit(1).count():
            firsts.append(round(time.perf_counter() - begin, 3))

    pool = BrickPool.create(spark, vm)
    versions, seconds = timed(lambda: stream_ingest.stream_build(pool, stream_ingest.slice_batches(spark, sf_dir, slices), preview))
    (_, batch_s) = timed(lambda: raycast.mip_image(ingest.build(opened.voxels, vm, "shards").voxels(level=0).join(F.broadcast(rays), ["x", "y"]).select("px", "py", "c", "v")).count())
    return {"versions": versions, "stream_s": seconds, "first_image_s": firsts[0] if firsts else None, "blocking_first_image_s": batch_s}


def run_alignment(spark: SparkSession, sf_dir: str, per_block: tuple[int, ...] = (20, 40)) -> dict:
    """Bricks rewritten and seconds when the scan comes in blocks of so many slices."""
    opened = volume(spark, sf_dir, "scan")
    out = {}
    for n in per_block:
        pool = BrickPool.create(spark, opened.vm)
        log = opened.voxels.withColumn("seq", F.lit(0))
        blocks, seconds = timed(lambda: ingest.insert_blocks(pool, log, n))
        updates = ingest.parent_updates(opened.voxels, opened.vm, n).agg(F.sum("updates")).first()[0]
        out[n] = {"blocks": blocks, "seconds": seconds, "brick_updates": updates}
    return out


def guarded_bruteforce(voxels: DataFrame, vm, samples: DataFrame, max_bytes: int) -> DataFrame:
    """The in-core baseline: every voxel at full resolution, refused if the volume exceeds ``max_bytes``."""
    size = vm.dims[0] * vm.dims[1] * vm.dims[2] * vm.channels * vm.voxel_bytes
    if size > max_bytes:
        raise MemoryError(f"the volume takes {size} bytes, more than the {max_bytes} there are")
    return raycast.fetch(samples, voxels)


def gallery(spark: SparkSession, sf_dir: str, folder: str, pixels: int = 64) -> list[str]:
    """Six pictures: three volumes, each as maximum projection and composited; heat colours for one channel, red, green and blue for three."""
    written = []
    for name in ("ribbon", "scan", "sales"):
        opened = volume(spark, sf_dir, name)
        vm = opened.vm
        rays = raycast.ortho_rays(spark, vm, pixels, pixels)
        hits = opened.pool.voxels(level=0).join(F.broadcast(rays), ["x", "y"]).selectExpr("px", "py", "z as i", "c", "v")
        top = raycast.mip_image(hits)
        if vm.channels == 1:
            r, g, b = raycast.heat(F.col("v").cast("double"), vm.hi)
            flat = top.select("px", "py", r.alias("r"), g.alias("g"), b.alias("b"))
        else:
            flat = top.groupBy("px", "py").agg(*(F.coalesce(F.max(F.when(F.col("c") == c, F.col("v") / vm.hi)), F.lit(0.0)).alias(k) for c, k in enumerate("rgb")))
        for kind, image in (("mip", flat), ("dvr", raycast.dvr_window(raycast.transfer(hits, vm.hi)))):
            written.append(f"{folder}/{name}-{kind}.ppm")
            raw_stack.write_image(image, written[-1], pixels, pixels)
    return written
