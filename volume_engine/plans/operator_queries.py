"""Queries of the operators around the methods, over the library's own relations, and of streamed building."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import sql as sqlfuncs
from ..operators import aberration, borders, octree, raycast, relations
from ..operators.pool import BrickPool
from ..sources.catalog import volume
from ..sources.volumes import scan_events, table
from ..streaming import stream_ingest
from . import oracle as O
from .more_queries import _PARTS, SCAN
from .queries import open_volume, register

# --- chromatic correction -----------------------------------------------------------------------
SHIFTS = [(dx, dy, 0) for dx in (-1, 0, 1) for dy in (-1, 0, 1)]


@register("aberration_resample", f"WITH {O.rays('scan')} SELECT px, py, c, max(v) AS v FROM (SELECT px, py, c, v FROM ray JOIN (SELECT x + CASE WHEN c = 1 THEN 1 ELSE 0 END AS x, y, z, c, v FROM vox) AS s USING (x, y)) AS h GROUP BY px, py, c")
def _(spark, sf_dir):
    v, vm = open_volume(spark, sf_dir, "scan")
    copied = aberration.resample_channel(v, 1, aberration.translation(-1, 0, 0), vm)
    rays = raycast.ortho_rays(spark, vm, O.SAMPLE, O.SAMPLE)
    return raycast.mip_image(copied.join(F.broadcast(rays), ["x", "y"]).select("px", "py", "c", "v"))


@register("aberration_sweep", f"{SCAN}, s AS (SELECT * FROM (VALUES {', '.join(map(str, SHIFTS))}) AS t(dx, dy, dz)) SELECT s.dx, s.dy, s.dz, count(*) AS voxels, sum(least(a.v, b.v))::BIGINT AS overlap FROM s, vox AS a, vox AS b WHERE a.c = 0 AND b.c = 1 AND a.x = b.x + s.dx AND a.y = b.y + s.dy AND a.z = b.z + s.dz GROUP BY s.dx, s.dy, s.dz")
def _(spark, sf_dir):
    return aberration.overlap(open_volume(spark, sf_dir, "scan")[0], 0, 1, SHIFTS)


# --- borders, sparse channels, levels by error ----------------------------------------
_STEPS = "range(-1, 2)"


@register("deferred_borders", f"""{SCAN}, w AS (SELECT DISTINCT (x + sx) // 8 AS ix, (y + sy) // 8 AS iy, (z + sz) // 8 AS iz, x, y, z, c, v FROM vox, dims, {_STEPS} AS a(sx), {_STEPS} AS b(sy), {_STEPS} AS d(sz)
      WHERE NOT (sx = 0 AND sy = 0 AND sz = 0) AND x + sx >= 0 AND y + sy >= 0 AND z + sz >= 0 AND x + sx < (dx + 7) // 8 * 8 AND y + sy < (dy + 7) // 8 * 8 AND z + sz < (dz + 7) // 8 * 8)
      SELECT ix, iy, iz, count(*) AS voxels, sum(v)::BIGINT AS total FROM w WHERE ix <> x // 8 OR iy <> y // 8 OR iz <> z // 8 GROUP BY 1, 2, 3""")
def _(spark, sf_dir):
    rows = borders.border_job(volume(spark, sf_dir, "scan").pool).filter("level = 0")
    return rows.groupBy("ix", "iy", "iz").agg(F.count("*").alias("voxels"), F.sum("v").alias("total"))


@register("eager_border_updates", f"""{SCAN}, own AS (SELECT DISTINCT z // 8 AS block, l AS level, (x // 8) >> CAST(l AS INT) AS ix, (y // 8) >> CAST(l AS INT) AS iy, (z // 8) >> CAST(l AS INT) AS iz FROM vox, meta, range(0, 21) AS t(l) WHERE l <= top),
    near AS (SELECT DISTINCT block, level, ix + sx AS ix, iy + sy AS iy, iz + sz AS iz FROM own, dims, {_STEPS} AS a(sx), {_STEPS} AS b(sy), {_STEPS} AS d(sz)
      WHERE ix + sx BETWEEN 0 AND (dx - 1) // (8 << level) AND iy + sy BETWEEN 0 AND (dy - 1) // (8 << level) AND iz + sz BETWEEN 0 AND (dz - 1) // (8 << level))
    SELECT level, count(*) AS neighbours FROM near WHERE NOT EXISTS (SELECT 1 FROM own AS o WHERE o.block = near.block AND o.level = near.level AND o.ix = near.ix AND o.iy = near.iy AND o.iz = near.iz) GROUP BY level""")
def _(spark, sf_dir):
    v, vm = open_volume(spark, sf_dir, "scan")
    return borders.eager_border_updates(v, vm, 8).filter("neighbours > 0")


@register("sparse_channel_pack", f"WITH {O.bricks('scan')} SELECT level, sum(CAST(bmax - bmin >= 3276.75 AS INT))::BIGINT * 512 AS stored FROM stats GROUP BY level")
def _(spark, sf_dir):
    opened = volume(spark, sf_dir, "scan")
    return octree.pack_sparse(opened.pool.bricks(), opened.vm, 3276.75).groupBy("level").agg(F.sum(F.size("body")).alias("stored"))


@register("error_lod", f"WITH {O.nodes('ribbon', 25.6, 1)}, leaf AS (SELECT key FROM nodes WHERE level = 0) SELECT leaf.key, coalesce((SELECT max(n.level) FROM nodes AS n WHERE n.subspread < 25.6 AND n.key = leaf.key >> CAST(3 * n.level AS INT)), 0) AS level FROM leaf")
def _(spark, sf_dir):
    opened = volume(spark, sf_dir, "ribbon")
    return octree.error_level(opened.nodes(25.6), opened.vm, 25.6)


# --- filters and joins ---------------------------------------------------------------------------
@register("filter_box", f"{SCAN} SELECT c, count(*) AS n, sum(v)::BIGINT AS total FROM vox WHERE x BETWEEN 3 AND 40 AND y BETWEEN 10 AND 59 AND z BETWEEN 12 AND 77 GROUP BY c")
def _(spark, sf_dir):
    cells = volume(spark, sf_dir, "scan").pool.region({"x": (3, 40), "y": (10, 59), "z": (12, 77)}, 0)
    return cells.groupBy("c").agg(F.count("*").alias("n"), F.sum("v").alias("total"))


@register("filter_clip_halfspace", f"{SCAN} SELECT c, count(*) AS n, sum(v)::BIGINT AS total FROM vox WHERE (x + 0.5) + 2 * (y + 0.5) - (z + 0.5) - 20 >= 0 GROUP BY c")
def _(spark, sf_dir):
    from ..operators.render import clipped

    return clipped(open_volume(spark, sf_dir, "scan")[0], [(1, 2, -1, -20)]).groupBy("c").agg(F.count("*").alias("n"), F.sum("v").alias("total"))


_BOXES = [(k, 5 * k, 7 * k, 9 * k, 5 * k + 11, 7 * k + 9, 9 * k + 20) for k in range(12)]
_BOX_COLUMNS = "box, x0, y0, z0, x1, y1, z1"


@register("box_overlap_join", f"{SCAN}, b AS (SELECT * FROM (VALUES {', '.join(map(str, _BOXES))}) AS t({_BOX_COLUMNS})), k AS (SELECT DISTINCT x // 8 AS ix, y // 8 AS iy, z // 8 AS iz FROM vox) SELECT box, ix, iy, iz FROM b, k WHERE 8 * ix <= x1 AND 8 * ix + 7 >= x0 AND 8 * iy <= y1 AND 8 * iy + 7 >= y0 AND 8 * iz <= z1 AND 8 * iz + 7 >= z0")
def _(spark, sf_dir):
    opened = volume(spark, sf_dir, "scan")
    boxes = spark.createDataFrame(_BOXES, ", ".join(f"{c} int" for c in _BOX_COLUMNS.split(", ")))
    return relations.bricks_in_boxes(opened.pool.bricks(), boxes, opened.vm, 0).select("box", "ix", "iy", "iz")


@register("asof_event_view", "SELECT e.event_id, v.event_id AS view_id, CAST(floor(v.value * 100) AS BIGINT) AS view_value FROM (SELECT * FROM events WHERE event_type = 'purchase') AS e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') AS v ON e.user_id = v.user_id AND e.event_id >= v.event_id")
def _(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.expr("cast(floor(value * 100) as bigint)").alias("value"))
    right = e.filter("event_type = 'view'").select("user_id", "event_id", F.struct(F.col("event_id").alias("view_id"), F.col("value").alias("view_value")).alias("view"))
    found = relations.as_of(e.filter("event_type = 'purchase'").select("user_id", "event_id"), right, "user_id", "event_id", "view")
    return found.select("event_id", "view.view_id", "view.view_value")


# --- aggregation, pivoting, windows, top-k ---------------------------------------------------------
@register("agg_distinct_bricks", f"{SCAN} SELECT c, count(DISTINCT {O.morton('x // 8', 'y // 8', 'z // 8')}) AS bricks FROM vox GROUP BY c")
def _(spark, sf_dir):
    return volume(spark, sf_dir, "scan").pool.stats().filter("level = 0").groupBy("c").agg(F.count("*").alias("bricks"))


@register("intensity_histogram", f"{SCAN} SELECT c, v // 4096 AS bin, count(*) AS n FROM vox GROUP BY c, v // 4096")
def _(spark, sf_dir):
    return volume(spark, sf_dir, "scan").pool.voxels(level=0).groupBy("c", F.expr("v div 4096").alias("bin")).agg(F.count("*").alias("n"))


@register("unpivot_channels", f"{SCAN}, b AS (SELECT x // 8 AS ix, y // 8 AS iy, z // 8 AS iz, c, sum(v)::BIGINT AS total FROM vox GROUP BY 1, 2, 3, 4) SELECT ix, iy, iz, c, total FROM b")
def _(spark, sf_dir):
    bricks = volume(spark, sf_dir, "scan").pool.bricks().filter("level = 0")
    wide = bricks.select("ix", "iy", "iz", *(F.expr(f"if(known[{c}] > 0, bsum[{c}], null)").alias(f"c{c}") for c in range(3)))
    rows = wide.unpivot(["ix", "iy", "iz"], ["c0", "c1", "c2"], "name", "total").filter("total is not null")
    return rows.select("ix", "iy", "iz", F.expr("cast(substr(name, 2) as int)").alias("c"), "total")


@register("lag_slice_delta", f"{SCAN}, s AS (SELECT z, c, sum(v)::BIGINT AS total FROM vox GROUP BY z, c) SELECT z, c, total, total - coalesce(lag(total) OVER (PARTITION BY c ORDER BY z), 0) AS delta FROM s")
def _(spark, sf_dir):
    s = open_volume(spark, sf_dir, "scan")[0].groupBy("z", "c").agg(F.sum("v").alias("total"))  # a row per slice and channel
    return s.withColumn("delta", F.col("total") - F.coalesce(F.lag("total").over(Window.partitionBy("c").orderBy("z")), F.lit(0)))


@register("topk_dense_bricks", f"{SCAN}, b AS (SELECT {O.morton('x // 8', 'y // 8', 'z // 8')} AS key, count(*) AS voxels FROM vox GROUP BY 1) SELECT key, voxels FROM b ORDER BY voxels DESC, key LIMIT 20")
def _(spark, sf_dir):
    rows = volume(spark, sf_dir, "scan").pool.bricks().filter("level = 0").select("key", F.expr("aggregate(known, 0L, (a, k) -> a + k)").alias("voxels"))
    return rows.orderBy(F.desc("voxels"), "key").limit(20)


@register("slice_of_timestamp", "SELECT date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) * 4 + hour(ts) // 6 AS z, min(event_id) AS first_event, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf_dir):
    z = F.expr("timestampdiff(HOUR, timestamp_ntz'2024-01-01', date_trunc('DAY', ts)) div 6 + hour(ts) div 6")
    return table(spark, sf_dir, "events").groupBy(z.alias("z")).agg(F.min("event_id").alias("first_event"), F.count("*").alias("n"))


@register("array_brick_minmax", f"WITH {O.voxels('ribbon')} SELECT {O.morton('x // 4', 'y // 4', 'z // 4')} AS key, min(v) AS lo, max(v) AS hi, count(*) AS known FROM vox GROUP BY 1")
def _(spark, sf_dir):
    rows = volume(spark, sf_dir, "ribbon").pool.bricks().filter("level = 0").select("key", F.expr("filter(body, v -> v is not null)").alias("cells"))
    return rows.select("key", F.array_min("cells").alias("lo"), F.array_max("cells").alias("hi"), F.size("cells").alias("known"))


@register("channel_map", f"SELECT user_id, sum(CAST(event_type = 'view' AS INT))::BIGINT AS view, sum(CAST(event_type = 'click' AS INT))::BIGINT AS click, sum(CAST(event_type = 'purchase' AS INT))::BIGINT AS purchase FROM events WHERE event_type IN ('view', 'click', 'purchase') GROUP BY user_id")
def _(spark, sf_dir):
    per = table(spark, sf_dir, "events").filter("event_type in ('view', 'click', 'purchase')").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("channels"))  # three entries at most
    return maps.select("user_id", *(F.coalesce(F.try_element_at("channels", F.lit(k)), F.lit(0)).alias(k) for k in ("view", "click", "purchase")))


# --- SQL surface ---------------------------------------------------------------------------------
@register("sqludf_morton", f"{SCAN}, bk AS (SELECT DISTINCT x // 8 AS ix, y // 8 AS iy, z // 8 AS iz FROM vox) SELECT key, key >> 3 AS parent, 8 * key + 5 AS child FROM (SELECT {O.morton('ix', 'iy', 'iz')} AS key FROM bk) AS q")
def _(spark, sf_dir):
    opened = volume(spark, sf_dir, "scan")
    sqlfuncs.register(spark, opened.vm)
    text = "SELECT morton3(ix, iy, iz) AS key, parent_key(morton3(ix, iy, iz)) AS parent, child_key(morton3(ix, iy, iz), 5) AS child FROM {bricks} WHERE level = 0"
    return spark.sql(text, bricks=opened.pool.bricks())


@register("udtf_octant_children", f"WITH {O.voxels('scan')}, bk AS (SELECT DISTINCT {O.morton('x // 16', 'y // 16', 'z // 16')} AS key FROM vox) SELECT key, o AS octant, 8 * key + o AS child FROM bk, range(0, 8) AS t(o)")
def _(spark, sf_dir):
    sqlfuncs.register_tables(spark)
    keys = volume(spark, sf_dir, "scan").pool.bricks().filter("level = 1").select("key")
    return spark.sql("SELECT key, octant, child FROM {keys} AS k, LATERAL octant_children(k.key)", keys=keys)


# --- streams ---------------------------------------------------------------------------------------
@register("stream_slices_batch_equiv", f"WITH {O.mipmap('scan')} SELECT level, c, count(*) AS cells, sum(v)::BIGINT AS total FROM mip GROUP BY level, c")
def _(spark, sf_dir):
    pool = BrickPool.create(spark, open_volume(spark, sf_dir, "scan")[1])
    stream_ingest.stream_build(pool, stream_ingest.slice_batches(spark, sf_dir, 24))
    return pool.voxels().groupBy("level", "c").agg(F.count("*").alias("cells"), F.sum("v").alias("total"))


@register("stream_late_slice", f"SELECT z, count(*) AS n, sum(v)::BIGINT AS total FROM ({_PARTS}) AS e GROUP BY z")
def _(spark, sf_dir):
    return stream_ingest.late_slices(spark, sf_dir)


_RUNS = """SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS begins, count(*) AS n, sum(CAST(floor(value * 100) AS BIGINT))::BIGINT AS total FROM (
    SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS run FROM (
      SELECT *, CAST(ts >= coalesce(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOURS, ts) AS INT) AS fresh FROM events WHERE event_type IN ('view', 'click', 'purchase')) AS a) AS b GROUP BY user_id, run"""


@register("stream_session_runs", _RUNS)
def _(spark, sf_dir):
    return stream_ingest.session_runs(spark, sf_dir)


@register("scan_monitor_health", f"SELECT z, count(*) AS n, round(avg(v), 6) AS mean, sum(CAST(v >= 45000 AS INT))::BIGINT AS saturated, CAST(count(DISTINCT c) < 3 AS BIGINT) AS missing_channel FROM ({_PARTS}) AS e GROUP BY z")
def _(spark, sf_dir):
    parts = scan_events(stream_ingest.event_stream(spark, sf_dir).drop("at"))
    watched = parts.groupBy("z").agg(F.count("*").alias("n"), F.avg("v").alias("mean"), F.count_if(F.col("v") >= 45000).alias("saturated"), (F.size(F.collect_set("c")) < 3).alias("missing_channel"))
    return stream_ingest.run_to_end(watched, "complete")
