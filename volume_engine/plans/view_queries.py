"""Queries of perspective views, level choice, filtering, intermixing and the measures of a pass."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.grid import morton3
from ..operators import camera as cam
from .. import storage
from ..operators import filtering, fullframe, octree, paging, raycast, render
from ..sources.catalog import volume
from . import oracle as O
from .more_queries import _CAND, _REQ, resolved_of, upload_candidates
from .queries import HI, hits_of, nodes_of, open_volume, register, stats_of

VIEW = cam.Camera((-60.0, 40.0, -90.0), (32.0, 32.0, 32.0))
STEP = 2.0
_RESIDENT = "(level = 0 AND key % 7 = 0 OR level = 1 AND key % 3 = 0 OR level = 2 AND key % 2 = 0 OR level = 3)"


def _d(v: float) -> str:
    return f"CAST('{v!r}' AS DOUBLE)"


def _rays_sql() -> str:
    b = VIEW.basis()
    half, w, h = _d(0.5), _d(float(VIEW.width)), _d(float(VIEW.height))
    aim = ", ".join(f"{_d(b['forward'][k])} + u * {_d(b['right'][k])} + v * {_d(b['up'][k])} AS w{a}" for k, a in enumerate("xyz"))
    slab = {a: (f"({_d(0.0)} - o{a}) / d{a}", f"({_d(64.0)} - o{a}) / d{a}") for a in "xyz"}
    enter = ", ".join(f"least({p}, {q})" for p, q in slab.values())
    leave = ", ".join(f"greatest({p}, {q})" for p, q in slab.values())
    return f"""pix AS (SELECT px, py, ({_d(2.0)} * (px + {half}) / {w} - 1) * {_d(VIEW.slope * VIEW.width / VIEW.height)} AS u, ({_d(1.0)} - {_d(2.0)} * (py + {half}) / {h}) * {_d(VIEW.slope)} AS v FROM range(0, {VIEW.width}) AS a(px), range(0, {VIEW.height}) AS b(py)),
    aim AS (SELECT px, py, {aim} FROM pix), dir AS (SELECT px, py, {', '.join(f'{_d(VIEW.eye[k])} AS o{a}' for k, a in enumerate('xyz'))}, {', '.join(f'w{a} / sqrt(wx * wx + wy * wy + wz * wz) AS d{a}' for a in 'xyz')} FROM aim),
    pray AS (SELECT *, greatest({enter}, {_d(0.0)}) AS enter, least({leave}) AS leave FROM dir),
    psteps AS (SELECT *, unnest(range(0, CAST(floor((leave - enter) / {_d(STEP)}) AS BIGINT))) AS i FROM pray WHERE enter < leave),
    pt AS (SELECT *, enter + (i + {half}) * {_d(STEP)} AS t FROM psteps),
    psample AS (SELECT px, py, i, t, {', '.join(f'least(63, greatest(0, CAST(floor(o{a} + d{a} * t) AS BIGINT))) AS {a}' for a in 'xyz')} FROM pt)"""


def _levels_sql(top: int = 3) -> str:
    level = " + ".join(f"CAST(t * {_d(VIEW.pixel_angle)} >= {_d(float(1 << l))} AS BIGINT)" for l in range(1, top + 1))
    return f"plod AS (SELECT *, {level} AS level FROM psample), pkey AS (SELECT *, {O.morton('(x >> CAST(level AS INT)) // 8', '(y >> CAST(level AS INT)) // 8', '(z >> CAST(level AS INT)) // 8')} AS key FROM plod)"


_RESOLVE_SQL = f"""pres AS (SELECT level, key FROM nodes WHERE {_RESIDENT}),
    pup AS (SELECT s.*, coalesce(n.homog, 1) AS flat, r0.key IS NOT NULL AS h0, CASE WHEN coalesce(n.homog, 1) = 1 THEN 3 WHEN r0.key IS NOT NULL THEN 0 WHEN r1.key IS NOT NULL THEN 1 WHEN r2.key IS NOT NULL THEN 2 ELSE 3 END AS up
      FROM pkey AS s LEFT JOIN nodes AS n ON n.level = s.level AND n.key = s.key LEFT JOIN pres AS r0 ON r0.level = s.level AND r0.key = s.key
      LEFT JOIN pres AS r1 ON r1.level = s.level + 1 AND r1.key = s.key >> 3 LEFT JOIN pres AS r2 ON r2.level = s.level + 2 AND r2.key = s.key >> 6)"""
_FULL = f"WITH {O.nodes('sales', 3276.75, 3)}, {_rays_sql()}, {_levels_sql()}, {_RESOLVE_SQL}"


def _image_sql(name: str, source: str, up: str) -> str:
    at = ", ".join(f"{a} >> CAST(level + {up} AS INT) AS {a}" for a in "xyz")
    return f"""{name} AS (SELECT px, py, c, max(v) AS v FROM (SELECT px, py, m.c, m.v FROM (SELECT px, py, level + {up} AS level, {at} FROM {source} WHERE {up} < 3) AS s JOIN mip AS m USING (level, x, y, z)
      UNION ALL SELECT px, py, c, avg AS v FROM {source} AS s JOIN (SELECT *, {O.morton('ix', 'iy', 'iz')} AS key FROM stats) AS a ON a.level = s.level AND a.key = s.key WHERE {up} = 3) AS q GROUP BY px, py, c)"""


_IMAGE = f"{_FULL}, {_image_sql('img', 'pup', 'up')}"
_ERROR = f"{_IMAGE}, pall AS (SELECT px, py, x, y, z, level, key, CASE WHEN flat = 1 THEN 3 ELSE 0 END AS up FROM pup), {_image_sql('truth', 'pall', 'up')}"


def view_of(spark, sf_dir):
    v, vm = open_volume(spark, sf_dir, "sales")
    rays = cam.perspective_rays(spark, VIEW, vm)
    return v, vm, rays, cam.choose_level(cam.sample_perspective(rays, vm, STEP), VIEW, vm)


def resolved_view(spark, sf_dir, everything: bool = False):
    samples = view_of(spark, sf_dir)[3]
    opened = volume(spark, sf_dir, "sales")
    nodes = opened.nodes(3276.75)
    resident = nodes.select("level", "key") if everything else nodes.filter(_RESIDENT).select("level", "key")
    averages = opened.pool.stats().select("level", morton3(F.col("ix"), F.col("iy"), F.col("iz"), opened.vm.key_bits).alias("key"), "c", "avg")
    return cam.resolve_at(samples, nodes, resident), opened.pool, averages


def fetched(spark, sf_dir, mode: str = "full_frame"):
    """Intensities of the view's samples by mode, through the pool's bricks."""
    opened = volume(spark, sf_dir, "sales")
    nodes = opened.nodes(3276.75)
    averages = opened.pool.stats().select("level", morton3(F.col("ix"), F.col("iy"), F.col("iz"), opened.vm.key_bits).alias("key"), "c", "avg")
    resolved = render.resolve(view_of(spark, sf_dir)[3], nodes, nodes.filter(_RESIDENT).select("level", "key"), mode)
    return render.fetch(resolved, opened.pool.bricks(), averages, opened.vm)


@register("perspective_rays", f"WITH {_rays_sql()} SELECT px, py, round(dx, 6) AS dx, round(dy, 6) AS dy, round(dz, 6) AS dz, CAST(enter < leave AS BIGINT) AS hit FROM pray")
def _(spark, sf_dir):
    return view_of(spark, sf_dir)[2].select("px", "py", "dx", "dy", "dz", "hit")


@register("optimal_lod", f"WITH {_rays_sql()}, {_levels_sql()} SELECT level, count(*) AS samples, count(DISTINCT key) AS bricks FROM pkey GROUP BY level")
def _(spark, sf_dir):
    return view_of(spark, sf_dir)[3].groupBy("level").agg(F.count("*").alias("samples"), F.count_distinct("key").alias("bricks"))


@register("metric_lod_histogram", f"{_FULL} SELECT level, up, count(*) AS samples, sum(CAST(flat = 0 AND NOT h0 AS INT))::BIGINT AS asking FROM pup GROUP BY level, up")
def _(spark, sf_dir):
    return resolved_view(spark, sf_dir)[0].groupBy("level", "up").agg(F.count("*").alias("samples"), F.count_if("asks").alias("asking"))


@register("full_frame_image", f"{_IMAGE} SELECT px, py, c, v FROM img")
def _(spark, sf_dir):
    return render.image(fetched(spark, sf_dir), "mip", None)


def _mode_image(up: str) -> str:
    return f"{_FULL}, pmode AS (SELECT px, py, i, x, y, z, level, key, {up} AS up FROM pup), {_image_sql('img', 'pmode', 'up')} SELECT px, py, c, v FROM img"


for _name, _mode, _up in (("base_basic_image", "basic", "CASE WHEN flat = 0 AND h0 THEN 0 ELSE 3 END"), ("base_avg_only_image", "average", "3"), ("direct_image", "direct", "CASE WHEN flat = 1 THEN 3 ELSE 0 END")):
    @register(_name, _mode_image(_up))
    def _(spark, sf_dir, mode=_mode):
        return render.image(fetched(spark, sf_dir, mode), "mip", None)


_HITS = f"""{_FULL}, hit AS (SELECT px, py, i, m.c, m.v FROM (SELECT px, py, i, level + up AS level, {', '.join(f'{a} >> CAST(level + up AS INT) AS {a}' for a in 'xyz')} FROM pup WHERE up < 3) AS s JOIN mip AS m USING (level, x, y, z)
      UNION ALL SELECT px, py, i, c, avg AS v FROM pup AS s JOIN (SELECT *, {O.morton('ix', 'iy', 'iz')} AS key FROM stats) AS a ON a.level = s.level AND a.key = s.key WHERE up = 3)"""


@register("full_frame_dvr", f"{_HITS}, {O.shade(65535)}, {O.dvr()}")
def _(spark, sf_dir):
    return render.image(fetched(spark, sf_dir), "dvr", lambda f: raycast.transfer(f, 65535))


@register("sample_source_kind", f"{_FULL} SELECT CASE WHEN flat = 1 THEN 'homogeneous' WHEN up = 0 THEN 'self' WHEN up = 1 THEN 'parent' WHEN up = 2 THEN 'grandparent' ELSE 'average' END AS kind, count(*) AS samples FROM pup GROUP BY 1")
def _(spark, sf_dir):
    return resolved_view(spark, sf_dir)[0].groupBy("kind").agg(F.count("*").alias("samples"))


@register("used_and_requested", f"""{_FULL}, u AS (SELECT DISTINCT level + up AS level, key >> CAST(3 * up AS INT) AS key FROM pup WHERE up < 3),
    q AS (SELECT DISTINCT level + j AS level, key >> CAST(3 * j AS INT) AS key FROM pup, meta, range(0, 3) AS t(j) WHERE flat = 0 AND NOT h0 AND level + j <= top)
    SELECT coalesce(u.level, q.level) AS level, coalesce(u.key, q.key) AS key, CAST(u.key IS NOT NULL AS BIGINT) + 2 * CAST(q.key IS NOT NULL AS BIGINT) AS flags FROM u FULL JOIN q ON u.level = q.level AND u.key = q.key""")
def _(spark, sf_dir):
    return render.flags(resolved_view(spark, sf_dir)[0], volume(spark, sf_dir, "sales").vm.top)


#: Opaque from an intensity of 30000 on: what lies behind such a sample is hidden.
_OPAQUE = [(c, 0, 30000, *k, 0.0, *k, 1.0) for c, k in raycast.COLOURS.items()] + [(c, 30000, 65536, *k, 1.0, *k, 1.0) for c, k in raycast.COLOURS.items()]
_OPAQUE_SQL = f"""WITH {O.rays('sales')}, shaded AS (SELECT *, least(1.0::DOUBLE, v / 30000.0::DOUBLE) AS a, CAST(c = 0 AS INT) * 1.0 AS r, CAST(c = 1 AS INT) * 1.0 AS g, CAST(c = 2 AS INT) * 1.0 AS b FROM hit),
    front AS (SELECT *, CASE WHEN coalesce(max(CAST(a >= 1 AS INT)) OVER before, 0) = 1 THEN 0 ELSE exp(coalesce(sum(CASE WHEN a < 1 THEN ln(1 - a) ELSE 0 END) OVER before, 0)) END AS t FROM shaded WINDOW before AS (PARTITION BY px, py ORDER BY i, c ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))"""
_OPAQUE_IMAGE = f"{_OPAQUE_SQL} SELECT px, py, round(sum(t * a * r), 6) AS r, round(sum(t * a * g), 6) AS g, round(sum(t * a * b), 6) AS b, round(sum(t * a), 6) AS a FROM front GROUP BY px, py"


def opaque_samples(spark, sf_dir):
    return raycast.transfer_table(hits_of(spark, sf_dir, "sales")[0], _OPAQUE)


for _name, _form in (("dvr_opaque_window", raycast.dvr_window), ("dvr_opaque_fold", raycast.dvr_fold), ("dvr_opaque_segments", lambda s: raycast.dvr_segments(s, 8)), ("intermix_opaque", lambda s: filtering.intermix(s, "accumulation"))):
    @register(_name, _OPAQUE_IMAGE)
    def _(spark, sf_dir, form=_form):
        return form(opaque_samples(spark, sf_dir)).select("px", "py", *"rgba")


SLABS = 8


def slab_reader(spark, sf_dir, k: int):
    """Reads, shades and gives the samples of one depth slab for the rays that still go on: bricks elsewhere are not opened."""
    opened = volume(spark, sf_dir, "sales")
    vm = opened.vm
    lo, hi = k * vm.dims[2] // SLABS, (k + 1) * vm.dims[2] // SLABS - 1
    rays = raycast.ortho_rays(spark, vm, O.SAMPLE, O.SAMPLE)

    def read(going):
        cells = opened.pool.region({"z": (lo, hi)}, 0)
        hit = cells.join(F.broadcast(rays.join(going, ["px", "py"])), ["x", "y"]).selectExpr("px", "py", "z as i", "c", "v")
        return raycast.transfer_table(hit, _OPAQUE)

    return read


def wavefront(spark, sf_dir):
    _, _, rays = hits_of(spark, sf_dir, "sales")
    return raycast.dvr_wavefront([slab_reader(spark, sf_dir, k) for k in range(SLABS)], rays, 0.95, storage.keep)


_STOPPED = f"{_OPAQUE_SQL} SELECT px, py, round(sum(t * a * r), 6) AS r, round(sum(t * a * g), 6) AS g, round(sum(t * a * b), 6) AS b, round(sum(t * a), 6) AS a, count(*) AS samples FROM front WHERE 1 - t < 0.95 GROUP BY px, py"


@register("dvr_wavefront", _STOPPED)
def _(spark, sf_dir):
    return wavefront(spark, sf_dir)[0].filter("samples > 0")


@register("metric_early_stop_fetches", f"{_OPAQUE_SQL}, slab AS (SELECT *, i * {SLABS} // 64 AS slab FROM front), going AS (SELECT px, py, slab, first(t ORDER BY i, c) AS start FROM slab GROUP BY px, py, slab) SELECT slab.slab AS slab, sum(CAST(1 - start < 0.95 AS INT))::BIGINT AS fetched FROM slab JOIN going USING (px, py, slab) GROUP BY slab.slab")
def _(spark, sf_dir):
    spent = wavefront(spark, sf_dir)[1]
    return spark.createDataFrame([(k, n) for k, (_, n) in enumerate(spent)], "slab long, fetched long")


@register("metric_image_error", f"""{_ERROR}, d AS (SELECT coalesce(img.c, truth.c) AS c, coalesce(img.v, 0) - coalesce(truth.v, 0) AS d FROM img FULL JOIN truth ON img.px = truth.px AND img.py = truth.py AND img.c = truth.c)
    SELECT c, count(*) AS pixels, round(avg(abs(d)), 6) AS mae, max(abs(d)) AS worst, round(CASE WHEN avg(d * d) > 0 THEN 10 * log10({_d(65535.0 * 65535.0)} / avg(CAST(d * d AS DOUBLE))) END, 6) AS psnr FROM d GROUP BY c""")
def _(spark, sf_dir):
    views = [render.image(fetched(spark, sf_dir, mode), "mip", None) for mode in ("full_frame", "direct")]
    return cam.image_error(*views, 65535)


# --- filtering and borders -------------------------------------------------------------------
_QUARTERS = f"WITH {O.rays('sales')}, smp AS (SELECT px, py, z // 4 AS i, x, y, z, (px % 4) * 0.25::DOUBLE AS fx, (py % 4) * 0.25::DOUBLE AS fy, (z // 4 % 4) * 0.25::DOUBLE AS fz FROM (SELECT px, py, x, y, unnest(range(t0, t1, 4)) AS z FROM ray) AS s)"
_CORNERS = f"{_QUARTERS}, cor AS (SELECT *, (CASE ax WHEN 1 THEN fx ELSE 1 - fx END) * (CASE ay WHEN 1 THEN fy ELSE 1 - fy END) * (CASE az WHEN 1 THEN fz ELSE 1 - fz END) AS w FROM smp, range(0, 2) AS a(ax), range(0, 2) AS b(ay), range(0, 2) AS d(az))"
_GLOBAL = f"{_CORNERS} SELECT px, py, i, c, round(sum(w * v), 6) AS v FROM cor JOIN vox ON vox.x = cor.x + ax AND vox.y = cor.y + ay AND vox.z = cor.z + az WHERE w > 0 GROUP BY px, py, i, c"
_CLAMP = f"{_CORNERS} SELECT px, py, i, c, round(sum(w * v), 6) AS v FROM cor JOIN vox ON " + " AND ".join(f"vox.{a} = least(cor.{a} + a{a}, cor.{a} // 8 * 8 + 7)" for a in "xyz") + " WHERE w > 0 GROUP BY px, py, i, c"


def quarter_samples(spark, sf_dir):
    v, vm = open_volume(spark, sf_dir, "sales")
    s = raycast.sample_rays(raycast.ortho_rays(spark, vm, O.SAMPLE, O.SAMPLE), 4)
    s = s.select("px", "py", "i", *(F.col(a).cast("int").alias(a) for a in "xyz"))
    return s.withColumns({"fx": F.expr("px % 4 * 0.25D"), "fy": F.expr("py % 4 * 0.25D"), "fz": F.expr("i % 4 * 0.25D")}), v, vm


for _name, _border, _sql in (("trilinear_sample", "global", _GLOBAL), ("trilinear_halo_equals_global", "overlap", _GLOBAL), ("trilinear_clamped", "clamp", _CLAMP)):
    @register(_name, _sql)
    def _(spark, sf_dir, border=_border):
        s, v, vm = quarter_samples(spark, sf_dir)
        return filtering.trilinear(s, v, vm, border)


@register("base_neighbour_fetch_count", f"{_CORNERS}, held AS (SELECT DISTINCT x // 8 AS jx, y // 8 AS jy, z // 8 AS jz FROM vox), f AS (SELECT px, py, i, count(DISTINCT CASE WHEN (x + ax) // 8 <> x // 8 OR (y + ay) // 8 <> y // 8 OR (z + az) // 8 <> z // 8 THEN (jx * 100 + jy) * 100 + jz END) AS k FROM cor LEFT JOIN held ON jx = (x + ax) // 8 AND jy = (y + ay) // 8 AND jz = (z + az) // 8 WHERE w > 0 GROUP BY px, py, i) SELECT count(*) AS samples, sum(CAST(k > 0 AS INT))::BIGINT AS border_samples, sum(k)::BIGINT AS fetches FROM f")
def _(spark, sf_dir):
    s, v, vm = quarter_samples(spark, sf_dir)
    return filtering.neighbour_fetches(s, vm, v)


# --- intermixing ------------------------------------------------------------------------------
_SHADED = f"WITH {O.rays('scan')}, {O.shade(65535)}"


def _front(part: str, order: str) -> str:
    return f"exp(coalesce(sum(ln(1 - a)) OVER (PARTITION BY {part} ORDER BY {order} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))"


_SUMS = "sum(t * a * r) AS r, sum(t * a * g) AS g, sum(t * a * b) AS b, sum(t * a) AS a"
_ROUND = "round(least(1, sum(r)), 6) AS r, round(least(1, sum(g)), 6) AS g, round(least(1, sum(b)), 6) AS b, round(least(1, sum(a)), 6) AS a"


@register("intermix_image_level", f"{_SHADED}, f AS (SELECT *, {_front('px, py, c', 'i')} AS t FROM shaded), one AS (SELECT px, py, c, {_SUMS} FROM f GROUP BY px, py, c) SELECT px, py, {_ROUND} FROM one GROUP BY px, py")
def _(spark, sf_dir):
    return filtering.intermix(raycast.transfer(hits_of(spark, sf_dir, "scan")[0], HI["scan"]), "image")


@register("intermix_sample_level", f"{_SHADED}, m AS (SELECT px, py, i, coalesce(sum(a * r) / nullif(sum(a), 0), 0) AS r, coalesce(sum(a * g) / nullif(sum(a), 0), 0) AS g, coalesce(sum(a * b) / nullif(sum(a), 0), 0) AS b, 1 - exp(sum(ln(1 - a))) AS a FROM shaded GROUP BY px, py, i), f AS (SELECT *, {_front('px, py', 'i')} AS t FROM m), one AS (SELECT px, py, {_SUMS} FROM f GROUP BY px, py) SELECT px, py, {_ROUND} FROM one GROUP BY px, py")
def _(spark, sf_dir):
    return filtering.intermix(raycast.transfer(hits_of(spark, sf_dir, "scan")[0], HI["scan"]), "sample")


# --- wavelet sizes and measures of a pass ---------------------------------------------------------
def _haar_sql(levels: int = 3) -> str:
    parts = [O.voxels("sales"), "h0 AS (SELECT x, y, z, c, v FROM vox)"]
    for l in range(levels):
        sign = [" * ".join([f"(1 - 2 * ({a} % 2))" for j, a in enumerate("xyz") if k >> j & 1] or ["1"]) for k in range(8)]
        sums = ", ".join(f"sum(v * {s})::BIGINT AS s{k}" for k, s in enumerate(sign))
        parts.append(f"t{l} AS (SELECT x // 2 AS x, y // 2 AS y, z // 2 AS z, c, {sums} FROM (SELECT * FROM h{l}) AS q GROUP BY 1, 2, 3, 4), h{l + 1} AS (SELECT x, y, z, c, s0 AS v FROM t{l})")
    details = "sum(" + " + ".join(f"CAST(s{k} <> 0 AS INT)" for k in range(1, 8)) + ")::BIGINT"
    return "WITH " + ", ".join(parts) + " " + " UNION ALL ".join(f"SELECT {l} AS level, c, count(*) AS blocks, {details} AS details, {details} * 2 AS bytes FROM t{l} GROUP BY c" for l in range(levels))


@register("base_haar_bytes", _haar_sql())
def _(spark, sf_dir):
    return filtering.haar_sizes(open_volume(spark, sf_dir, "sales")[0], 3)


@register("metric_requests_per_pass", f"{_REQ} SELECT level, count(*) AS bricks, sum(waiting)::BIGINT AS waiting FROM req GROUP BY level")
def _(spark, sf_dir):
    return fullframe.requests(resolved_of(spark, sf_dir)[0]).groupBy("level").agg(F.count("*").alias("bricks"), F.sum("waiting").alias("waiting"))


@register("metric_slot_occupancy", f"{_CAND} SELECT count(*) AS slots, sum(used)::BIGINT AS used, count(*) * 3072 AS bytes FROM (SELECT * FROM cand ORDER BY used DESC, level DESC, resident DESC, key LIMIT 64) AS q")
def _(spark, sf_dir):
    held = paging.plan_uploads(upload_candidates(spark, sf_dir), 64, "coarse_first")
    return held.agg(F.count("*").alias("slots"), F.sum("used").alias("used"), (F.count("*") * 3072).alias("bytes"))


@register("metric_traversal_steps", f"WITH {O.nodes('scan', 3276.75, 3)}, per AS (SELECT c, level, ix, iy, iz, CAST(smax - smin < 3276.75 AS INT) AS sub FROM stats) SELECT (SELECT sum(top - level)::BIGINT FROM kept, meta) AS shared_steps, (SELECT sum(top - level)::BIGINT FROM per AS a, meta WHERE NOT EXISTS (SELECT 1 FROM per AS p WHERE p.c = a.c AND p.level = a.level + 1 AND p.ix = a.ix // 2 AND p.iy = a.iy // 2 AND p.iz = a.iz // 2 AND p.sub = 1)) AS channel_steps")
def _(spark, sf_dir):
    nodes, vm = nodes_of(spark, sf_dir, "scan")
    shared = octree.collapse(nodes, vm).agg(F.sum(F.lit(vm.top) - F.col("level")).alias("shared_steps"))
    per = stats_of(spark, sf_dir, "scan")[0].select("c", "level", "ix", "iy", "iz", (F.col("smax") - F.col("smin") < 3276.75).alias("sub"))
    flat = per.filter("sub").select("c", (F.col("level") - 1).alias("level"), *(F.col(f"i{a}").alias(f"p{a}") for a in "xyz"))
    kept = per.withColumns({f"p{a}": F.expr(f"i{a} div 2") for a in "xyz"}).join(flat, ["c", "level", "px", "py", "pz"], "left_anti")
    return shared.join(kept.agg(F.sum(F.lit(vm.top) - F.col("level")).alias("channel_steps")))
