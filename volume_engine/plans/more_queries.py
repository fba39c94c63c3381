"""Queries of incremental building, residency, paging, borders, deltas, streams and the operators around them."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .. import storage
from ..functions import codec, grid
from ..operators import fullframe, ingest, mipmap, node_buffer, octree, paging, raycast, traverse
from ..operators import pool as brick_pool
from ..operators.pool import BrickPool
from ..sources.catalog import volume
from ..sources.volumes import table
from ..streaming import stream_ingest
from . import oracle as O
from .queries import _KEPT, _WORD, nodes_of, open_volume, register, scan_bricks

SCAN = f"WITH {O.voxels('scan')}"
MIPSUM = "SELECT level, c, count(*) AS cells, sum(v)::BIGINT AS total FROM mip GROUP BY level, c"


def summary(pool: BrickPool) -> DataFrame:
    return pool.voxels().groupBy("level", "c").agg(F.count("*").alias("cells"), F.sum("v").alias("total"))


def pool_of_blocks(spark, sf_dir, *blocks) -> BrickPool:
    """The scan volume built block by block; each block is a condition, or a condition and a value."""
    v, vm = open_volume(spark, sf_dir, "scan")
    pool = BrickPool.create(spark, vm)
    for b in blocks:
        where, value = b if isinstance(b, tuple) else (b, "v")
        pool.insert(v.filter(where).withColumn("v", F.expr(value)))
    return pool


# --- incremental ---------------------------------------------------------------------------
@register("incr_insert_sequence", f"WITH {O.mipmap('scan')} {MIPSUM}")
def _(spark, sf_dir):
    return summary(pool_of_blocks(spark, sf_dir, "z < 40", "z >= 40"))


@register("incr_order_invariance", f"WITH {O.mipmap('scan')} {MIPSUM}")
def _(spark, sf_dir):
    return summary(pool_of_blocks(spark, sf_dir, "z * 37 % 120 >= 60", "z * 37 % 120 < 60"))


@register("incr_channel_by_channel", f"WITH {O.mipmap('scan')} {MIPSUM}")
def _(spark, sf_dir):
    return summary(pool_of_blocks(spark, sf_dir, "c = 2", "c = 0", "c = 1"))


@register("incr_overwrite", f"WITH {O.mipmap('scan')} {MIPSUM}")
def _(spark, sf_dir):
    return summary(pool_of_blocks(spark, sf_dir, ("true", "if(z = 5, v * 2, v)"), "z = 5"))


_STATSUM = "SELECT level, c, count(*) AS bricks, sum(bsum)::BIGINT AS total, sum(smin)::BIGINT AS smin, sum(smax)::BIGINT AS smax, sum(n)::BIGINT AS n FROM stats GROUP BY level, c"


@register("incr_batch_equals_sequence", f"WITH {O.bricks('scan')} {_STATSUM}")
def _(spark, sf_dir):
    v, vm = open_volume(spark, sf_dir, "scan")
    pool = BrickPool.create(spark, vm)
    ingest.insert_blocks(pool, v.withColumn("seq", F.lit(0)), 40)
    return pool.stats().groupBy("level", "c").agg(F.count("*").alias("bricks"), F.sum("bsum").alias("total"), F.sum("smin").alias("smin"), F.sum("smax").alias("smax"), F.sum("n").alias("n"))


for _way in ("channel", "octant", "none"):
    @register(f"build_by_{_way}", f"WITH {O.bricks('scan')} {_STATSUM}")
    def _(spark, sf_dir, way=_way):
        v, vm = open_volume(spark, sf_dir, "scan")
        return ingest.build(v, vm, way).stats().groupBy("level", "c").agg(F.count("*").alias("bricks"), F.sum("bsum").alias("total"), F.sum("smin").alias("smin"), F.sum("smax").alias("smax"), F.sum("n").alias("n"))


@register("brick_parent_from_children", f"WITH {O.mipmap('scan')} SELECT x, y, z, c, v FROM m1")
def _(spark, sf_dir):
    opened = volume(spark, sf_dir, "scan")
    parents = brick_pool.parents_of(opened.pool.bricks(), opened.vm, 0).withColumn("level", F.lit(1))
    return brick_pool.unpacked(parents, opened.vm).drop("level")


@register("border_stats", f"WITH {O.bricks('scan')} SELECT level, ix, iy, iz, c, n, bmin, bmax, avg FROM stats WHERE n < 512")
def _(spark, sf_dir):
    return volume(spark, sf_dir, "scan").pool.stats().filter("n < 512").select("level", "ix", "iy", "iz", "c", "n", "bmin", "bmax", "avg")


@register("octree_siblings", f"WITH {O.nodes('scan', 3276.75, 3)} SELECT p.level - 1 AS level, 8 * count(*) - (SELECT count(*) FROM kept AS k WHERE k.level = p.level - 1) AS siblings FROM kept AS p WHERE p.level > 0 AND p.subhomog = 0 GROUP BY p.level")
def _(spark, sf_dir):
    n, vm = nodes_of(spark, sf_dir, "scan")
    return octree.siblings(octree.collapse(n, vm)).groupBy("level").agg(F.count("*").alias("siblings"))


@register("homog_all_channels", f"WITH {O.nodes('scan', 3276.75, 3)}, spans AS (SELECT level, ix, iy, iz, min(bmax - bmin) AS least FROM stats GROUP BY 1, 2, 3, 4) SELECT nodes.level, count(*) AS bricks, sum(homog)::BIGINT AS all_channels, sum(CAST(least < 3276.75 AS INT))::BIGINT AS some_channel FROM nodes JOIN spans USING (level, ix, iy, iz) GROUP BY nodes.level")
def _(spark, sf_dir):
    opened = volume(spark, sf_dir, "scan")
    spans = F.expr("transform(filter(sequence(0, size(known) - 1), c -> known[c] > 0), c -> bmax[c] - bmin[c])")
    rows = opened.pool.bricks().select("level", spans.alias("spans"))
    return rows.groupBy("level").agg(F.count("*").alias("bricks"), F.count_if(F.array_max("spans") < 3276.75).alias("all_channels"), F.count_if(F.array_min("spans") < 3276.75).alias("some_channel"))


@register("late_overwrite", f"{SCAN} SELECT x, y, z, c, v FROM vox")
def _(spark, sf_dir):
    v, _ = open_volume(spark, sf_dir, "scan")
    log = v.withColumn("seq", F.lit(2)).unionByName(v.filter("z = 5").withColumns({"v": F.col("v") + 7, "seq": F.lit(1)}))
    return ingest.latest(log)


for _name, _per in (("slice_parent_updates", 1), ("aligned_parent_updates", 8)):
    @register(_name, f"{SCAN} SELECT level, count(*) AS updates FROM (SELECT DISTINCT z // {_per} AS block, l AS level, (x // 8) // (1 << l) AS ix, (y // 8) // (1 << l) AS iy, (z // 8) // (1 << l) AS iz FROM vox, meta, range(0, 21) AS t(l) WHERE l <= top) AS q GROUP BY level")
    def _(spark, sf_dir, per=_per):
        v, vm = open_volume(spark, sf_dir, "scan")
        return ingest.parent_updates(v, vm, per)


@register("aligned_vs_slice_updates", " UNION ALL ".join(f"SELECT * FROM ({SCAN} SELECT {p} AS per_block, level, count(*) AS updates FROM (SELECT DISTINCT z // {p} AS block, l AS level, (x // 8) // (1 << l) AS ix, (y // 8) // (1 << l) AS iy, (z // 8) // (1 << l) AS iz FROM vox, meta, range(0, 21) AS t(l) WHERE l <= top) AS q GROUP BY level) AS p{p}" for p in (1, 5, 8)))
def _(spark, sf_dir):
    v, vm = open_volume(spark, sf_dir, "scan")
    return reduce(DataFrame.unionByName, (ingest.parent_updates(v, vm, p).withColumn("per_block", F.lit(p)) for p in (1, 5, 8)))


@register("touched_nodes", f"{SCAN} SELECT level, count(*) AS nodes FROM (SELECT DISTINCT l AS level, (x // 8) // (1 << l) AS ix, (y // 8) // (1 << l) AS iy, (z // 8) // (1 << l) AS iz FROM vox, meta, range(0, 21) AS t(l) WHERE l <= top AND z = 30) AS q GROUP BY level")
def _(spark, sf_dir):
    v, vm = open_volume(spark, sf_dir, "scan")
    return ingest.touched_nodes(v.filter("z = 30"), vm).groupBy("level").agg(F.count("*").alias("nodes"))


@register("partial_tree_render", f"WITH {O.rays('scan')} SELECT px, py, c, max(v) AS v FROM hit WHERE i < 40 GROUP BY px, py, c")
def _(spark, sf_dir):
    pool = pool_of_blocks(spark, sf_dir, "z < 40", "z >= 40")
    rays = raycast.ortho_rays(spark, pool.vm, O.SAMPLE, O.SAMPLE)
    early = pool.voxels(pool.commits[0], 0)  # the tree as it was after the first block
    return raycast.mip_image(early.join(F.broadcast(rays), ["x", "y"]).select("px", "py", "c", "v"))


LINE = grid.VolumeMeta("line", (16, 1, 1), (4, 4, 4))
LINE_BLOCKS = [(0, [1, 5, 1, 5]), (12, [5, 1, 2, 4]), (4, [3, 3, 3, 3]), (8, [1, 3, 3, 5])]


def line_pool(spark) -> BrickPool:
    """The one-dimensional example: four blocks that arrive out of order."""
    pool = BrickPool.create(spark, LINE)
    for x0, values in LINE_BLOCKS:
        pool.insert(spark.createDataFrame([(x0 + i, 0, 0, 0, v) for i, v in enumerate(values)], "x int, y int, z int, c int, v long"))
    return pool


# step, level, brick, average, homogeneous, subtree homogeneous under a threshold of one
_STATES = "(1, 0, 0, 3, 0, 0), (1, 1, 0, 1, 0, 0), (1, 2, 0, 0, 0, 0), (2, 0, 0, 3, 0, 0), (2, 0, 3, 3, 0, 0), (2, 1, 0, 1, 0, 0), (2, 1, 1, 1, 0, 0), (2, 2, 0, 1, 0, 0), (3, 0, 0, 3, 0, 0), (3, 0, 1, 3, 1, 1), (3, 0, 3, 3, 0, 0), (3, 1, 0, 3, 1, 0), (3, 1, 1, 1, 0, 0), (3, 2, 0, 2, 0, 0), (4, 0, 0, 3, 0, 0), (4, 0, 1, 3, 1, 1), (4, 0, 2, 3, 0, 0), (4, 0, 3, 3, 0, 0), (4, 1, 0, 3, 1, 0), (4, 1, 1, 3, 0, 0), (4, 2, 0, 3, 1, 0)"


@register("worked_example_states", f"SELECT * FROM (VALUES {_STATES}) AS t(step, level, brick, average, homog, subhomog)")
def _(spark, sf_dir):
    pool = line_pool(spark)
    steps = [octree.nodes_of_bricks(pool.bricks(v), LINE, 1).select(F.lit(k + 1).alias("step"), "level", F.col("ix").alias("brick"), F.col("avg0").alias("average"), "homog", "subhomog") for k, v in enumerate(pool.commits)]
    return reduce(DataFrame.unionByName, steps)


@register("worked_example_1d", "SELECT * FROM (VALUES (0, 0, 1), (0, 1, 5), (0, 2, 1), (0, 3, 5), (0, 4, 3), (0, 5, 3), (0, 6, 3), (0, 7, 3), (0, 8, 1), (0, 9, 3), (0, 10, 3), (0, 11, 5), (0, 12, 5), (0, 13, 1), (0, 14, 2), (0, 15, 4), (1, 0, 3), (1, 1, 3), (1, 2, 3), (1, 3, 3), (1, 4, 2), (1, 5, 4), (1, 6, 3), (1, 7, 3), (2, 0, 3), (2, 1, 3), (2, 2, 3), (2, 3, 3)) AS t(level, x, v)")
def _(spark, sf_dir):
    return line_pool(spark).voxels().select("level", "x", "v")


# --- residency, full frame, uploads -----------------------------------------------------------
_NODES = f"WITH {O.nodes('scan', 3276.75, 3)}"
_RES = "(level = 0 AND key % 7 = 0 OR level = 1 AND key % 3 = 0 OR level = 2 AND key % 2 = 0)"
_RESOLVED = f"""{_NODES}, res AS (SELECT level, key FROM nodes WHERE {_RES}),
 resolved AS (SELECT key, CASE WHEN homog = 1 THEN 'homogeneous' WHEN EXISTS (SELECT 1 FROM res AS r WHERE r.level = 0 AND r.key = n.key) THEN 'self'
  WHEN EXISTS (SELECT 1 FROM res AS r WHERE r.level = 1 AND r.key = n.key >> 3) THEN 'parent' WHEN EXISTS (SELECT 1 FROM res AS r WHERE r.level = 2 AND r.key = n.key >> 6) THEN 'grandparent' ELSE 'average' END AS kind FROM nodes AS n WHERE level = 0)"""


def resolved_of(spark, sf_dir, all_coarse: bool = False):
    n, vm = nodes_of(spark, sf_dir, "scan")
    n = n.withColumn("homog", F.col("homog").cast("int"))
    resident = n.filter("level = 2" if all_coarse else _RES).select("level", "key")
    return fullframe.resolve_source(n.filter("level = 0").select("key", "homog"), resident), n


@register("full_frame_fallback", f"{_RESOLVED} SELECT key, kind FROM resolved")
def _(spark, sf_dir):
    return resolved_of(spark, sf_dir)[0].select("key", "kind")


@register("metric_sample_sources", f"{_RESOLVED} SELECT kind, count(*) AS bricks FROM resolved GROUP BY kind")
def _(spark, sf_dir):
    return resolved_of(spark, sf_dir)[0].groupBy("kind").agg(F.count("*").alias("bricks"))


_REQ = f"{_RESOLVED}, req AS (SELECT l AS level, key >> CAST(3 * l AS INT) AS key, count(*) AS waiting FROM resolved, range(0, 3) AS t(l) WHERE kind IN ('parent', 'grandparent', 'average') GROUP BY 1, 2)"


@register("full_frame_requests", f"{_REQ} SELECT level, key, waiting FROM req")
def _(spark, sf_dir):
    return fullframe.requests(resolved_of(spark, sf_dir)[0])


@register("full_frame_no_avg", "SELECT 0 AS averages")
def _(spark, sf_dir):
    return resolved_of(spark, sf_dir, True)[0].agg(F.count_if(F.expr("kind = 'average'")).alias("averages"))


def upload_candidates(spark, sf_dir):
    resolved, n = resolved_of(spark, sf_dir)
    req = fullframe.requests(resolved)
    resident = n.filter(_RES).select("level", "key", F.lit(1).alias("resident"))
    both = req.join(resident, ["level", "key"], "full")
    return both.select("level", "key", F.when(F.col("waiting").isNotNull(), 1).otherwise(0).alias("used"), F.coalesce("resident", F.lit(0)).alias("resident"), F.coalesce("waiting", F.lit(0)).alias("waiting"), F.expr("key * 31 % 1009").alias("seq"))


_CAND = f"{_REQ}, cand AS (SELECT coalesce(q.level, r.level) AS level, coalesce(q.key, r.key) AS key, CAST(q.key IS NOT NULL AS INT) AS used, CAST(r.key IS NOT NULL AS INT) AS resident, coalesce(waiting, 0) AS waiting FROM req AS q FULL JOIN res AS r ON q.level = r.level AND q.key = r.key)"


@register("upload_full_frame", f"{_CAND} SELECT level, key FROM cand ORDER BY used DESC, level DESC, resident DESC, key LIMIT 64")
def _(spark, sf_dir):
    return paging.plan_uploads(upload_candidates(spark, sf_dir), 64, "coarse_first").select("level", "key")


@register("upload_fifo", f"{_CAND} SELECT level, key FROM cand WHERE resident = 0 ORDER BY key * 31 % 1009, level DESC, key LIMIT 64")
def _(spark, sf_dir):
    return paging.plan_uploads(upload_candidates(spark, sf_dir), 64, "fifo").select("level", "key")


@register("upload_refine", f"{_CAND} SELECT level, key FROM cand WHERE resident = 0 ORDER BY waiting DESC, level DESC, key LIMIT 64")
def _(spark, sf_dir):
    return paging.plan_uploads(upload_candidates(spark, sf_dir), 64, "replace_all").select("level", "key")


@register("upload_budget", f"{_CAND} SELECT level, key, running FROM (SELECT level, key, sum(1536) OVER (ORDER BY waiting DESC, level DESC, key)::BIGINT AS running FROM (SELECT * FROM cand WHERE resident = 0 ORDER BY waiting DESC, level DESC, key LIMIT 64) AS p) AS q WHERE running <= 40000")
def _(spark, sf_dir):
    planned = paging.plan_uploads(upload_candidates(spark, sf_dir), 64, "replace_all").withColumn("bytes", F.lit(1536))
    return paging.within_budget(planned, [F.desc("waiting"), F.desc("level"), F.col("key")], "bytes", 40000).select("level", "key", "running")


@register("flag_buffer", f"{_RESOLVED} SELECT level, key >> CAST(3 * level AS INT) AS key, bit_or(flag) AS flags FROM (SELECT 0 AS level, key, CASE WHEN kind IN ('homogeneous', 'self') THEN 1 ELSE 2 END AS flag FROM resolved UNION ALL SELECT 1, key, CASE kind WHEN 'parent' THEN 1 ELSE 2 END FROM resolved WHERE kind NOT IN ('homogeneous', 'self')) AS f GROUP BY 1, 2")
def _(spark, sf_dir):
    r = resolved_of(spark, sf_dir)[0]
    own = r.select(F.lit(0).alias("level"), "key", F.when(F.col("kind").isin("homogeneous", "self"), 1).otherwise(2).alias("flag"))
    up = r.filter("kind not in ('homogeneous', 'self')").select(F.lit(1).alias("level"), F.shiftright("key", 3).alias("key"), F.when(F.col("kind") == "parent", 1).otherwise(2).alias("flag"))
    return own.unionByName(up).groupBy("level", "key").agg(F.bit_or("flag").alias("flags"))


# --- the same relations through set operations, ranks, ranges and semi-joins ---------------------
def requests_of(spark, sf_dir):
    """Bricks asked for (level, key, waiting) and resident (level, key), and the nodes."""
    resolved, n = resolved_of(spark, sf_dir)
    return fullframe.requests(resolved), n.filter(_RES).select("level", "key"), n


@register("rank_upload", f"{_REQ} SELECT level, key, rk FROM (SELECT level, key, row_number() OVER (PARTITION BY level ORDER BY waiting DESC, key) AS rk FROM req) AS q WHERE rk <= 3")
def _(spark, sf_dir):
    req = requests_of(spark, sf_dir)[0]
    return req.select("level", "key", F.row_number().over(Window.partitionBy("level").orderBy(F.desc("waiting"), "key")).alias("rk")).filter("rk <= 3")


@register("running_budget", f"{_REQ} SELECT level, key, run FROM (SELECT level, key, sum(3072 * waiting) OVER (PARTITION BY level ORDER BY waiting DESC, key ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)::BIGINT AS run FROM req) AS q WHERE run <= 100000")
def _(spark, sf_dir):
    run = F.sum(F.col("waiting") * 3072).over(Window.partitionBy("level").orderBy(F.desc("waiting"), "key").rowsBetween(Window.unboundedPreceding, 0))
    return requests_of(spark, sf_dir)[0].select("level", "key", run.alias("run")).filter("run <= 100000")


@register("ntile_pages", f"{_NODES} SELECT level, tile, count(*) AS bricks, min(key) AS first_key FROM (SELECT level, key, ntile(8) OVER (PARTITION BY level ORDER BY key) AS tile FROM nodes) AS q GROUP BY level, tile")
def _(spark, sf_dir):
    tile = F.ntile(8).over(Window.partitionBy("level").orderBy("key"))
    return requests_of(spark, sf_dir)[2].select("level", "key", tile.alias("tile")).groupBy("level", "tile").agg(F.count("*").alias("bricks"), F.min("key").alias("first_key"))


@register("topk_requests", f"{_REQ} SELECT level, key, waiting FROM req ORDER BY waiting DESC, level DESC, key LIMIT 10")
def _(spark, sf_dir):
    return requests_of(spark, sf_dir)[0].orderBy(F.desc("waiting"), F.desc("level"), "key").limit(10)


for _name, _sql, _how in (
    ("setop_union_requests", "UNION", lambda a, b: a.union(b).distinct()), ("setop_intersect_resident", "INTERSECT", lambda a, b: a.intersect(b)), ("setop_except_missing", "EXCEPT", lambda a, b: a.subtract(b)),
):
    @register(_name, f"{_REQ} SELECT level, key FROM req {_sql} SELECT level, key FROM res")
    def _(spark, sf_dir, how=_how):
        req, resident, _ = requests_of(spark, sf_dir)
        return how(req.select(F.col("level").cast("int").alias("level"), "key"), resident)


_TOUCHED = f"touched AS (SELECT DISTINCT l AS level, {O.morton('(x // 8) >> CAST(l AS INT)', '(y // 8) >> CAST(l AS INT)', '(z // 8) >> CAST(l AS INT)')} AS key FROM vox, meta, range(0, 21) AS t(l) WHERE l <= top AND z = 30)"


@register("semi_touched", f"{_NODES}, {_TOUCHED} SELECT level, key, n FROM nodes WHERE EXISTS (SELECT 1 FROM touched AS t WHERE t.level = nodes.level AND t.key = nodes.key)")
def _(spark, sf_dir):
    opened = volume(spark, sf_dir, "scan")
    touched = ingest.touched_nodes(opened.voxels.filter("z = 30"), opened.vm)
    return opened.pool.bricks().join(touched, ["level", "ix", "iy", "iz"], "left_semi").select("level", "key", "n")


@register("anti_missing_children", f"{_NODES}, c AS (SELECT level - 1 AS level, 8 * key + o AS key FROM nodes, range(0, 8) AS t(o) WHERE level > 0) SELECT level, count(*) AS missing FROM c WHERE NOT EXISTS (SELECT 1 FROM nodes AS n WHERE n.level = c.level AND n.key = c.key) GROUP BY level")
def _(spark, sf_dir):
    n = volume(spark, sf_dir, "scan").pool.bricks().select("level", "key")
    children = n.filter("level > 0").select((F.col("level") - 1).alias("level"), F.explode(F.expr("transform(sequence(0, 7), o -> 8 * key + o)")).alias("key"))
    return children.join(n, ["level", "key"], "left_anti").groupBy("level").agg(F.count("*").alias("missing"))


@register("cross_threshold", f"{_NODES} SELECT level, t, sum(CASE WHEN spread < t THEN 1 ELSE 0 END)::BIGINT AS homogeneous FROM nodes CROSS JOIN (VALUES (1000), (3000), (9000)) AS th(t) GROUP BY level, t")
def _(spark, sf_dir):
    limits = F.broadcast(spark.createDataFrame([(1000,), (3000,), (9000,)], "t int"))
    n = requests_of(spark, sf_dir)[2]
    return n.crossJoin(limits).groupBy("level", "t").agg(F.count_if(F.col("spread") < F.col("t")).alias("homogeneous"))


_BANDS = [(c, lo, hi, band / 4, 0.0, 0.0, 1.0, band / 4, 0.0, 0.0, 1.0) for c in range(3) for band, (lo, hi) in enumerate(((0, 10000), (10000, 30000), (30000, 65536)))]


@register("range_join_tf", f"{SCAN} SELECT c, band / 4 AS r, count(*) AS n FROM vox JOIN (VALUES (0, 0, 10000), (1, 10000, 30000), (2, 30000, 65536)) AS tf(band, lo, hi) ON v >= lo AND v < hi GROUP BY c, band")
def _(spark, sf_dir):
    shaded = raycast.transfer_table(open_volume(spark, sf_dir, "scan")[0], _BANDS)
    return shaded.groupBy("c", "r").agg(F.count("*").alias("n"))


# --- refinement --------------------------------------------------------------------------------
_SAMPLES = f"WITH {O.rays('scan')}, need AS (SELECT px, py, i, {O.morton('x // 8', 'y // 8', 'i // 8')} AS key FROM (SELECT DISTINCT px, py, x, y, i FROM ray JOIN (SELECT DISTINCT x, y, z AS i FROM vox) AS s USING (x, y)) AS h)"


def needed_samples(spark, sf_dir):
    v, vm = open_volume(spark, sf_dir, "scan")
    rays = raycast.ortho_rays(spark, vm, O.SAMPLE, O.SAMPLE)
    hit = v.select("x", "y", "z").distinct().join(F.broadcast(rays), ["x", "y"])
    return hit.select("px", "py", F.col("z").alias("i"), grid.morton3(F.expr("x div 8"), F.expr("y div 8"), F.expr("z div 8")).alias("key"))


@register("refine_pass1_state", f"{_SAMPLES} SELECT px, py, coalesce(min(CASE WHEN key % 3 <> 0 THEN i END), -1) AS halt FROM need GROUP BY px, py")
def _(spark, sf_dir):
    s = needed_samples(spark, sf_dir)
    return fullframe.halt_points(s, s.select("key").distinct().filter("key % 3 = 0")).withColumn("halt", F.coalesce("halt", F.lit(-1)))


@register("refine_total_bricks", f"{_SAMPLES} SELECT count(DISTINCT key) AS bricks FROM need")
def _(spark, sf_dir):
    return needed_samples(spark, sf_dir).agg(F.count_distinct("key").alias("bricks"))


@register("refine_final_equals_direct", f"WITH {O.rays('scan')}, {O.shade(65535)}, {O.dvr()}")
def _(spark, sf_dir):
    v, vm = open_volume(spark, sf_dir, "scan")
    rays = raycast.ortho_rays(spark, vm, O.SAMPLE, O.SAMPLE)
    key = grid.morton3(F.expr("x div 8"), F.expr("y div 8"), F.expr("z div 8"), vm.key_bits)
    hit = v.join(F.broadcast(rays), ["x", "y"]).select("px", "py", F.col("z").alias("i"), "c", "v", key.alias("key"))
    return fullframe.refine_image(raycast.transfer(hit, 65535), 128, storage.keep)[0]


# --- paging ------------------------------------------------------------------------------------
_TRACE = f"{SCAN}, bk AS (SELECT DISTINCT x // 8 AS ix, y // 8 AS iy, z // 8 AS iz FROM vox), trace AS (SELECT iy AS cache, row_number() OVER (PARTITION BY iy ORDER BY ix % 3, iz, ix) AS seq, {O.morton('ix', 'iy', 'iz')} >> 3 AS page FROM bk), d AS (SELECT a.cache, a.seq, a.page, (SELECT max(p.seq) FROM trace AS p WHERE p.cache = a.cache AND p.page = a.page AND p.seq < a.seq) AS prev FROM trace AS a), dist AS (SELECT cache, seq, page, CASE WHEN prev IS NULL THEN NULL ELSE (SELECT count(DISTINCT t.page) FROM trace AS t WHERE t.cache = d.cache AND t.seq > prev AND t.seq < d.seq) END AS distance FROM d)"


def trace_of(spark, sf_dir):
    b = scan_bricks(spark, sf_dir)
    seq = F.row_number().over(Window.partitionBy("iy").orderBy(F.expr("ix % 3"), "iz", "ix"))
    return b.select(F.col("iy").cast("long").alias("cache"), seq.cast("long").alias("seq"), F.shiftright(grid.morton3(F.col("ix"), F.col("iy"), F.col("iz")), 3).alias("page"))


@register("lru_distances", f"{_TRACE} SELECT cache, seq, page, coalesce(distance, -1) AS distance FROM dist")
def _(spark, sf_dir):
    return paging.stack_distances(trace_of(spark, sf_dir)).withColumn("distance", F.coalesce("distance", F.lit(-1)))


@register("lru_hits", f"{_TRACE} SELECT cache, count(*) AS accesses, sum(CAST(coalesce(distance < 8, false) AS INT))::BIGINT AS hits FROM dist GROUP BY cache")
def _(spark, sf_dir):
    t = trace_of(spark, sf_dir).select("cache", "seq", "page", *(F.lit(False).alias(k) for k in ("write", "pin", "unpin")))
    return paging.simulate_lru(t, 8).groupBy("cache").agg(F.count("*").alias("accesses"), F.sum("hit").alias("hits"))


@register("lru_evictions", f"{_TRACE}, m AS (SELECT cache, sum(CAST(NOT coalesce(distance < 8, false) AS INT))::BIGINT AS misses, least(8, count(DISTINCT page)) AS held FROM dist GROUP BY cache) SELECT cache, misses - held AS evictions FROM m")
def _(spark, sf_dir):
    t = trace_of(spark, sf_dir).select("cache", "seq", "page", *(F.lit(False).alias(k) for k in ("write", "pin", "unpin")))
    return paging.simulate_lru(t, 8).groupBy("cache").agg(F.count_if(F.expr("evicted >= 0")).alias("evictions"))


@register("metric_page_switches", f"{_TRACE} SELECT cap, sum(CAST(NOT coalesce(distance < cap, false) AS INT))::BIGINT AS loads FROM dist, (VALUES (2), (8), (1000000)) AS t(cap) GROUP BY cap")
def _(spark, sf_dir):
    caps = F.broadcast(spark.createDataFrame([(2,), (8,), (1000000,)], "cap long"))
    return paging.stack_distances(trace_of(spark, sf_dir)).join(caps).groupBy("cap").agg(F.count_if(F.expr("not coalesce(distance < cap, false)")).alias("loads"))


@register("page_assignment", f"{SCAN} SELECT {O.morton('x // 8', 'y // 8', 'z // 8')} >> 6 AS page, count(DISTINCT {O.morton('x // 8', 'y // 8', 'z // 8')}) AS bricks FROM vox GROUP BY 1")
def _(spark, sf_dir):
    b = scan_bricks(spark, sf_dir).select(grid.morton3(F.col("ix"), F.col("iy"), F.col("iz")).alias("key"))
    return b.groupBy(F.shiftright("key", 6).alias("page")).agg(F.count("*").alias("bricks"))


# --- borders -----------------------------------------------------------------------------------
_STEP = {2: "range(-1, 2)", 1: "range(-1, 1)"}
for _name, _sides in (("halo_bricks", 2), ("halo_one_sided_bricks", 1)):
    @register(_name, f"""{SCAN}, w AS (SELECT DISTINCT (x + sx) // 8 AS ix, (y + sy) // 8 AS iy, (z + sz) // 8 AS iz, x, y, z, c, v FROM vox, dims, {_STEP[_sides]} AS a(sx), {_STEP[_sides]} AS b(sy), {_STEP[_sides]} AS d(sz)
      WHERE NOT (sx = 0 AND sy = 0 AND sz = 0) AND x + sx >= 0 AND y + sy >= 0 AND z + sz >= 0 AND x + sx < (dx + 7) // 8 * 8 AND y + sy < (dy + 7) // 8 * 8 AND z + sz < (dz + 7) // 8 * 8)
      SELECT ix, iy, iz, count(*) AS voxels, sum(v)::BIGINT AS total FROM w WHERE ix <> x // 8 OR iy <> y // 8 OR iz <> z // 8 GROUP BY 1, 2, 3""")
    def _(spark, sf_dir, sides=_sides):
        v, vm = open_volume(spark, sf_dir, "scan")
        return fullframe.halo_voxels(v, vm, sides).groupBy("ix", "iy", "iz").agg(F.count("*").alias("voxels"), F.sum("v").alias("total"))


# --- deltas ------------------------------------------------------------------------------------
#: The scan when seven tenths of its slices had arrived, and later, whole, with a corner overwritten by background.
_EARLY = ("z < (SELECT max(z) + 1 FROM allvox) * 7 // 10",)
_LATER = ("", "CASE WHEN x < 16 AND y < 16 THEN 0 ELSE v END")


def words_sql(*changes: str) -> str:
    return f"WITH {O.nodes('scan', 3276.75, 3, *changes)}, w AS ({_WORD}) SELECT CAST((pow(8, top - level) - 1) / 7 AS BIGINT) + key AS idx, low + (payload << 24) AS word FROM w, meta"


_VERS = f"WITH o AS ({words_sql(*_EARLY)}), n AS ({words_sql(*_LATER)}), ev AS (SELECT coalesce(o.idx, n.idx) AS idx, CASE WHEN o.word IS NULL THEN 'create' WHEN n.word IS NULL THEN 'delete' WHEN o.word <> n.word THEN 'update' END AS kind, coalesce(n.word, 0) AS word FROM o FULL JOIN n ON o.idx = n.idx)"


def versions(spark, sf_dir):
    """Node buffers of two versions of one pool, and its declaration."""
    v, vm = open_volume(spark, sf_dir, "scan")
    early = vm.dims[2] * 7 // 10
    pool = pool_of_blocks(spark, sf_dir, f"z < {early}", (f"z >= {early} or x < 16 and y < 16", "if(x < 16 and y < 16, 0, v)"))
    return *(node_buffer.node_words(octree.collapse(octree.nodes_of_bricks(pool.bricks(k), vm, 3276.75), vm), vm).select("idx", "word") for k in pool.commits), vm


@register("delta_events", f"{_VERS} SELECT kind, idx, word FROM ev WHERE kind IS NOT NULL")
def _(spark, sf_dir):
    old, new, _ = versions(spark, sf_dir)
    return node_buffer.change_events(old, new)


@register("delta_apply_equals_rebuild", f"{_VERS} SELECT idx, word FROM n")
def _(spark, sf_dir):
    old, new, _ = versions(spark, sf_dir)
    return node_buffer.patch(old, node_buffer.change_events(old, new))


@register("metric_delta_size", f"{_VERS} SELECT sum(CAST(kind IS NOT NULL AS INT))::BIGINT AS sent, (SELECT count(*) FROM n) AS rebuilt FROM ev")
def _(spark, sf_dir):
    old, new, _ = versions(spark, sf_dir)
    sent = node_buffer.change_events(old, new).agg(F.count("*").alias("sent"))
    return sent.join(new.agg(F.count("*").alias("rebuilt")))


@register("base_rebuild_words", f"{_KEPT}, w AS ({_WORD}) SELECT (SELECT CAST((pow(8, top + 1) - 1) / 7 AS BIGINT) FROM meta) AS words, count(*) AS nodes, bit_xor(low + (payload << 24)) AS checksum FROM w")
def _(spark, sf_dir):
    n, vm = nodes_of(spark, sf_dir, "scan")
    words = node_buffer.node_words(octree.collapse(n, vm), vm)
    counts = node_buffer.level_counts(words, vm).agg(F.sum("words").alias("words"), F.sum("nodes").alias("nodes"))
    return counts.join(words.agg(F.bit_xor("word").alias("checksum")))  # words without a node are 0 and change no checksum


_SLOTS = "SELECT level, key, row_number() OVER (ORDER BY level DESC, key) - 1 AS slot FROM kept WHERE homog = 0 AND key % {} = 0"


@register("residency_patch", f"{_KEPT}, w AS ({_WORD}), s AS (SELECT * FROM ({_SLOTS.format(5)}) AS q WHERE slot < 64) SELECT w.level, w.key, CASE WHEN slot IS NULL THEN low + (payload << 24) ELSE low + 1 + (slot << 24) END AS word FROM w LEFT JOIN s ON w.level = s.level AND w.key = s.key")
def _(spark, sf_dir):
    n, vm = nodes_of(spark, sf_dir, "scan")
    kept = octree.collapse(n, vm)
    words = node_buffer.node_words(kept, vm)
    averages = kept.select("idx", codec.pack_averages([F.col(f"avg{c}") for c in range(vm.channels)]).alias("payload"))

    def slots(k: int) -> DataFrame:
        held = kept.filter(f"has_brick and key % {k} = 0").orderBy(F.desc("level"), "key").limit(64)  # the buffer's slots
        return held.select("idx", (F.row_number().over(Window.orderBy(F.desc("level"), "key")) - 1).alias("slot"))

    before = node_buffer.load(words.select("idx", "word"), slots(7), averages)
    return node_buffer.load(before, slots(5), averages).join(words.select("idx", "level", "key"), "idx").select("level", "key", "word")


@register("tier_of_request", f"{_REQ} SELECT req.level, req.key, req.key >> 6 AS page, CASE WHEN r.key IS NOT NULL THEN 'gpu' WHEN (req.key >> 6) % 2 = 0 THEN 'ram' ELSE 'disk' END AS tier FROM req LEFT JOIN res AS r ON r.level = req.level AND r.key = req.key")
def _(spark, sf_dir):
    resolved, n = resolved_of(spark, sf_dir)
    req = fullframe.requests(resolved)
    pages = req.select("level", F.shiftright("key", 6).alias("page")).distinct().filter("page % 2 = 0")
    return paging.serve_requests(req, n.filter(_RES).select("level", "key"), pages)


@register("dirty_writebacks", f"""{_TRACE}, e AS (SELECT *, CAST(NOT coalesce(distance < 8, false) AS INT) AS miss FROM dist), ep AS (SELECT *, sum(miss) OVER (PARTITION BY cache, page ORDER BY seq) AS epoch FROM e),
 g AS (SELECT cache, page, epoch, max(seq) AS last, max(CAST(seq % 3 = 0 AS INT)) AS dirty FROM ep GROUP BY cache, page, epoch),
 k AS (SELECT *, lead(epoch) OVER (PARTITION BY cache, page ORDER BY epoch) IS NOT NULL AS again, (SELECT count(DISTINCT t.page) FROM trace AS t WHERE t.cache = g.cache AND t.seq > g.last) AS later FROM g)
 SELECT cache, sum(CASE WHEN again OR later >= 8 THEN dirty ELSE 0 END)::BIGINT AS written FROM k GROUP BY cache""")
def _(spark, sf_dir):
    t = trace_of(spark, sf_dir).withColumns({"write": F.col("seq") % 3 == 0, "pin": F.lit(False), "unpin": F.lit(False)})
    return paging.simulate_lru(t, 8).groupBy("cache").agg(F.sum("written").alias("written"))


# --- baselines ---------------------------------------------------------------------------------
@register("base_bruteforce_image", f"WITH {O.rays('sales')} SELECT px, py, c, max(v) AS v FROM hit GROUP BY px, py, c")
def _(spark, sf_dir):
    v, vm = open_volume(spark, sf_dir, "sales")
    samples = raycast.sample_rays(raycast.ortho_rays(spark, vm, O.SAMPLE, O.SAMPLE))
    return raycast.mip_image(raycast.fetch(samples, v))


@register("base_avg_only_error", f"WITH {O.bricks('sales')}, a AS (SELECT ix, iy, iz, c, avg FROM b0) SELECT c, round(avg(abs(v - avg)), 6) AS mae, max(abs(v - avg)) AS worst FROM vox JOIN a ON vox.x // 8 = ix AND vox.y // 8 = iy AND vox.z // 8 = iz AND vox.c = a.c GROUP BY c".replace("SELECT c, round", "SELECT vox.c AS c, round").replace("GROUP BY c", "GROUP BY vox.c"))
def _(spark, sf_dir):
    v, vm = open_volume(spark, sf_dir, "sales")
    a = mipmap.brick_stats(v, vm, 0).select("ix", "iy", "iz", "c", "avg")
    rows = v.withColumns(grid.coords(0, vm)).join(a, ["ix", "iy", "iz", "c"])
    return rows.groupBy("c").agg(F.avg(F.abs(F.col("v") - F.col("avg"))).alias("mae"), F.max(F.abs(F.col("v") - F.col("avg"))).alias("worst"))


# --- streaming ---------------------------------------------------------------------------------
_PARTS = O.VOX["scan"].split("FROM (", 1)[1].rsplit(") AS e", 1)[0]


@register("stream_tumbling_slices", f"SELECT z, count(*) AS n, sum(v)::BIGINT AS total FROM ({_PARTS}) AS e GROUP BY z")
def _(spark, sf_dir):
    return stream_ingest.tumbling_slices(spark, sf_dir)


@register("stream_sliding_slab", f"SELECT slab, c, max(v) AS v FROM ({_PARTS}) AS e, range(0, 200) AS t(slab) WHERE z >= 2 * slab AND z < 2 * slab + 4 GROUP BY slab, c")
def _(spark, sf_dir):
    return stream_ingest.sliding_slab(spark, sf_dir)


@register("stream_dedup", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def _(spark, sf_dir):
    return stream_ingest.dedup(spark, sf_dir)


@register("stream_static_tf", f"SELECT CASE WHEN v < 10000 THEN 'dark' WHEN v < 30000 THEN 'mid' ELSE 'bright' END AS band, count(*) AS n FROM ({_PARTS}) AS e GROUP BY 1")
def _(spark, sf_dir):
    return stream_ingest.static_transfer(spark, sf_dir)


@register("scan_monitor_flags", f"SELECT z, n, total, CAST(total > 2 * coalesce(lag(total) OVER (ORDER BY z), total) AS BIGINT) AS jump FROM (SELECT z, count(*) AS n, sum(v)::BIGINT AS total FROM ({_PARTS}) AS e GROUP BY z) AS q")
def _(spark, sf_dir):
    slices = stream_ingest.tumbling_slices(spark, sf_dir)  # one row per slice
    return slices.withColumn("jump", F.col("total") > 2 * F.coalesce(F.lag("total").over(Window.orderBy("z")), F.col("total")))


# --- operators around the methods: one text for both engines ------------------------------------
BOTH = {
    "scan_parquet_lineitem": "SELECT count(*) AS n, sum(l_linenumber) AS s FROM lineitem",
    "scan_pruned_columns": "SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_quantity > 30 GROUP BY l_returnflag",
    "join_orders_lineitem": "SELECT o_orderstatus, count(*) AS n, max(l_quantity) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderstatus",
    "join_broadcast_nation": "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name, n_name",
    "agg_voxel_stats": "SELECT event_type, count(*) AS n, min(event_id) AS lo, max(event_id) AS hi, count(DISTINCT user_id) AS users FROM events GROUP BY event_type",
    "cube_axes": "SELECT coalesce(l_returnflag, 'all') AS f, coalesce(l_linestatus, 'all') AS s, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "grouping_sets_projections": "SELECT coalesce(n_regionkey, -1) AS r, coalesce(c_mktsegment, 'all') AS m, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY GROUPING SETS ((n_regionkey), (c_mktsegment))",
    "string_chunk_lengths": "SELECT item_id, length(text) AS n, upper(substr(text, 1, 4)) AS head FROM benchmark",
    "slab_rollup": "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name",
    "page_lengths": "SELECT page_id, length(html) AS n FROM pages WHERE url LIKE 'https:%'",
    "preview_hash_sample": "SELECT count(*) AS n FROM orders WHERE o_orderkey * 2654435 % 1000 < 100",
}
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "benchmark", "pages")


def _both(text: str):
    import re

    used = [t for t in TABLES if re.search(rf"\b{t}\b", text)]
    marked = text
    for t in used:
        marked = re.sub(rf"\b(FROM|JOIN) {t}\b", rf"\1 {{{t}}} AS {t}", marked)
    return lambda spark, sf_dir: spark.sql(marked, **{t: table(spark, sf_dir, t) for t in used})


for _name, _text in BOTH.items():
    register(_name, _text)(_both(_text))


@register("pivot_channels", "SELECT user_id, sum(CAST(event_type = 'view' AS INT))::BIGINT AS views, sum(CAST(event_type = 'click' AS INT))::BIGINT AS clicks FROM events WHERE event_type IN ('view', 'click') GROUP BY user_id")
def _(spark, sf_dir):
    e = table(spark, sf_dir, "events").filter("event_type in ('view', 'click')")
    p = e.groupBy("user_id").pivot("event_type", ["view", "click"]).agg(F.count(F.lit(1)))
    return p.select("user_id", F.coalesce("view", F.lit(0)).alias("views"), F.coalesce("click", F.lit(0)).alias("clicks"))


@register("json_props_axis", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n"))


@register("embedding_posexplode", "SELECT i, count(*) AS n, round(max(embedding[i + 1])::DOUBLE, 6) AS hi FROM embeddings, range(0, 64) AS t(i) GROUP BY i")
def _(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select(F.posexplode("embedding").alias("i", "e"))
    return e.groupBy("i").agg(F.count("*").alias("n"), F.max("e").cast("double").alias("hi"))


@register("asof_last_slice", "SELECT user_id, max(event_id) AS last_view, arg_max(CAST(floor(value * 100) AS BIGINT), event_id) AS v FROM events WHERE event_type = 'view' GROUP BY user_id")
def _(spark, sf_dir):
    e = table(spark, sf_dir, "events").filter("event_type = 'view'")  # as of the table's last event
    return e.groupBy("user_id").agg(F.max("event_id").alias("last_view"), F.max_by(F.expr("cast(floor(value * 100) as bigint)"), "event_id").alias("v"))


@register("recursive_ancestors", f"{SCAN}, bk AS (SELECT DISTINCT {O.morton('x // 8', 'y // 8', 'z // 8')} AS key FROM vox) SELECT l AS level, count(DISTINCT key >> CAST(3 * l AS INT)) AS nodes FROM bk, meta, range(0, 21) AS t(l) WHERE l <= top GROUP BY l")
def _(spark, sf_dir):
    opened = volume(spark, sf_dir, "scan")
    # the recursion runs over the levels alone, as Spark bounds the rows that one may make; the keys meet its result
    text = """WITH RECURSIVE up(level) AS (SELECT 0 UNION ALL SELECT level + 1 FROM up WHERE level < {top})
        SELECT level, count(DISTINCT shiftright(key, 3 * level)) AS nodes FROM {leaves} CROSS JOIN up GROUP BY level"""
    leaves = opened.pool.bricks().filter("level = 0").select("key")
    return spark.sql(text.replace("{top}", str(opened.vm.top)), leaves=leaves)


@register("parent_child_join", f"{_NODES} SELECT c.level, c.key, p.spread AS parent_spread FROM nodes AS c JOIN nodes AS p ON p.level = c.level + 1 AND p.key = c.key >> 3")
def _(spark, sf_dir):
    n, _ = nodes_of(spark, sf_dir, "scan")
    p = n.select((F.col("level") - 1).alias("level"), F.col("key").alias("pkey"), F.col("spread").alias("parent_spread"))
    return n.withColumn("pkey", F.shiftright("key", 3)).join(p, ["level", "pkey"]).select("level", "key", "parent_spread")


_LOCATE = f"WITH {O.nodes('ribbon', 25.6, 1)}, need AS (SELECT DISTINCT {O.morton('x // 4', 'y // 4', 'z // 4')} AS key FROM vox) SELECT need.key, min(kept.level) AS level FROM need, kept WHERE kept.key = need.key >> CAST(3 * kept.level AS INT) GROUP BY need.key"

for _name, _way in (("locate_nodes", traverse.locate_by_key), ("locate_nodes_by_level", traverse.locate_by_level), ("locate_nodes_sorted", traverse.locate_sorted)):
    @register(_name, _LOCATE)
    def _(spark, sf_dir, way=_way):
        n, vm = nodes_of(spark, sf_dir, "ribbon")
        return way(n.filter("level = 0").select("key"), octree.collapse(n, vm), vm.top)


@register("locate_per_channel", f"""WITH {O.nodes('scan', 3276.75, 3)}, need AS (SELECT key FROM nodes WHERE level = 0), per AS (SELECT c, level, ix, iy, iz, {O.morton('ix', 'iy', 'iz')} AS key, CAST(smax - smin < 3276.75 AS INT) AS sub FROM stats),
    tree AS (SELECT c, level, key FROM per AS a WHERE NOT EXISTS (SELECT 1 FROM per AS p WHERE p.c = a.c AND p.level = a.level + 1 AND p.key = a.key >> 3 AND p.sub = 1))
    SELECT need.key, c, min(tree.level) AS level FROM need, tree WHERE tree.key = need.key >> CAST(3 * tree.level AS INT) GROUP BY need.key, c""")
def _(spark, sf_dir):
    opened = volume(spark, sf_dir, "scan")
    bricks = opened.pool.bricks()
    return traverse.locate_per_channel(bricks.filter("level = 0").select("key"), traverse.channel_trees(bricks, 3, 3276.75), opened.vm.top)


@register("homogeneous_bricks", f"WITH {O.nodes('scan', 3276.75, 3)} SELECT level, key, avg0, avg1, avg2 FROM nodes WHERE homog = 1")
def _(spark, sf_dir):
    return nodes_of(spark, sf_dir, "scan")[0].filter("homog").select("level", "key", "avg0", "avg1", "avg2")


@register("metric_parent_updates", " UNION ALL ".join(f"SELECT * FROM ({SCAN} SELECT {p} AS per_block, count(*) AS updates, sum(CAST(level > 0 AS INT))::BIGINT AS parents FROM (SELECT DISTINCT z // {p} AS block, l AS level, (x // 8) // (1 << l) AS ix, (y // 8) // (1 << l) AS iy, (z // 8) // (1 << l) AS iz FROM vox, meta, range(0, 21) AS t(l) WHERE l <= top) AS q) AS p{p}" for p in (1, 8, 40)))
def _(spark, sf_dir):
    v, vm = open_volume(spark, sf_dir, "scan")
    each = (ingest.parent_updates(v, vm, p).agg(F.sum("updates").alias("updates"), F.sum(F.when(F.col("level") > 0, F.col("updates"))).alias("parents")).withColumn("per_block", F.lit(p)) for p in (1, 8, 40))
    return reduce(DataFrame.unionByName, each)
