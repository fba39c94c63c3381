"""Geometry, pyramid, incremental building, compositing, paging and refinement against small brute-force forms."""

import collections
import itertools
import math
import random
from functools import reduce

import numpy as np
import pytest
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from volume_engine import experiments, storage
from volume_engine.functions import codec, grid
from volume_engine.operators import aberration, borders, camera, eager, filtering, fullframe, ingest, mipmap, node_buffer, octree, paging, pool, raycast, relations, render, session
from volume_engine.plans import more_queries, queries, registry
from volume_engine.sources import raw_stack
from volume_engine.streaming import stream_ingest
from volume_engine.sources.volumes import open_volume

SF = "/root/testdata/sf0.001"


def rows(spark, cells):
    return spark.createDataFrame(cells, "x int, y int, z int, c int, v long")


def dense(vm, cells):
    a = np.zeros((*vm.dims, vm.channels), dtype=np.int64)
    for x, y, z, c, v in cells:
        a[x, y, z, c] = v
    return a


def half(a):
    out = np.zeros([-(-d // 2) for d in a.shape[:3]] + [a.shape[3]], dtype=np.int64)
    for x, y, z in itertools.product(*map(range, out.shape[:3])):
        cell = a[2 * x : 2 * x + 2, 2 * y : 2 * y + 2, 2 * z : 2 * z + 2]
        out[x, y, z] = cell.sum(axis=(0, 1, 2)) // (cell.shape[0] * cell.shape[1] * cell.shape[2])
    return out


@pytest.fixture(scope="module")
def volume(spark):
    rng = random.Random(4)
    vm = grid.VolumeMeta("t", (9, 7, 5), (2, 2, 2), 2)
    places = rng.sample(list(itertools.product(range(9), range(7), range(5), range(2))), 150)
    return vm, [(*p, rng.randrange(1, 100)) for p in places]


def test_levels_of_the_large_examples():
    assert grid.fit_levels((3865, 1966, 2893), (32, 32, 32)) == 7
    assert grid.fit_levels((2560, 2160, 751), (64, 64, 64)) == 6
    assert grid.fit_levels((1004, 1002, 1611), (64, 64, 64)) == 5
    assert grid.addressing_limits(9)["fits"] and not grid.addressing_limits(10)["fits"]
    assert grid.addressing_limits(8)["nodes"] == 2396745 and grid.addressing_limits(9)["address_bits"] == 25


def test_odd_bricks_are_refused():
    with pytest.raises(ValueError):
        grid.check_brick(33)


def test_mipmap_equals_dense(spark, volume):
    vm, cells = volume
    a = dense(vm, cells)
    for level, mip in enumerate(mipmap.build_mipmap(rows(spark, cells), vm)):
        got = dense(grid.VolumeMeta("l", a.shape[:3], vm.brick, 2), [tuple(r) for r in mip.select("x", "y", "z", "c", "v").collect()])
        assert (got == a).all(), level
        a = half(a)


def test_subtree_statistics_equal_dense(spark, volume):
    vm, cells = volume
    pyramid = [dense(vm, cells)]
    for _ in range(vm.top):
        pyramid.append(half(pyramid[-1]))
    for r in mipmap.pyramid_stats(rows(spark, cells), vm).collect():
        lo, hi = [], []
        for l in range(r.level + 1):
            side = 2 << (r.level - l)
            part = pyramid[l][r.ix * side : (r.ix + 1) * side, r.iy * side : (r.iy + 1) * side, r.iz * side : (r.iz + 1) * side, r.c]
            lo.append(part.min())
            hi.append(part.max())
        assert (r.smin, r.smax, r.bmin, r.bmax) == (min(lo), max(hi), lo[-1], hi[-1])


def test_pack_and_unpack(spark, volume):
    vm, cells = volume
    packed = mipmap.pack_bricks(rows(spark, cells), vm, 0)
    got = mipmap.unpack_bricks(packed, vm).filter("v != 0").select("x", "y", "z", "c", "v").collect()
    assert sorted(map(tuple, got)) == sorted(cells)


@pytest.mark.parametrize("brick", [(2, 2, 2), (3, 3, 3), (16, 8, 8)])
def test_blocks_in_any_order_with_overwrites(spark, volume, brick):
    """Also with odd bricks, whose parents' cells lie over two children, and with a root that is a leaf."""
    vm, cells = volume
    vm = vm.with_brick(*brick)
    shuffled = random.Random(brick[0]).sample(cells, len(cells))
    wrong = [(*c[:4], c[4] + 50) for c in shuffled[:40]]
    p = pool.BrickPool.create(spark, vm)
    for block in (wrong, shuffled[:90], shuffled[90:]):
        p.insert(rows(spark, block))
    want = mipmap.mipmap_rows(rows(spark, cells), vm).select("level", *"xyzcv").collect()
    assert sorted(map(tuple, p.voxels().select("level", *"xyzcv").collect())) == sorted(map(tuple, want))
    cols = ["level", "ix", "iy", "iz", "c", "n", "bmin", "bmax", "bsum", "avg", "smin", "smax"]
    same = [sorted(tuple(map(int, r)) for r in s.select(cols).collect()) for s in (p.stats(), mipmap.pyramid_stats(rows(spark, cells), vm))]
    assert same[0] == same[1]
    again = pool.open_pool(spark, vm, p.path)
    assert again.commits == [0, 1, 2] and again.compacted().bricks().count() == p.bricks().count()
    assert sorted(map(tuple, p.voxels(0, 0).select(*"xyzcv").collect())) == sorted(wrong)


def test_a_replayed_version_changes_nothing(spark, volume):
    vm, cells = volume
    p = pool.BrickPool.create(spark, vm)
    p.insert(rows(spark, cells[:80]))
    p.insert(rows(spark, cells[80:]))
    before = sorted(map(tuple, p.voxels().collect()))
    assert p.insert(rows(spark, cells[80:]), 1) == 1 and p.commits == [0, 1]
    assert sorted(map(tuple, p.voxels().collect())) == before
    p.insert(rows(spark, [(99, 0, 0, 0, 1), (0, 0, 0, 9, 1)]))  # outside the volume: an empty block
    assert p.commits == [0, 1, 2] and sorted(map(tuple, p.voxels().collect())) == before
    with pytest.raises(ValueError):
        p.insert(rows(spark, cells[:1]), 0)


def test_compaction_keeps_the_newest_bricks_and_the_last_version(spark, volume):
    vm, cells = volume
    p = pool.BrickPool.create(spark, vm)
    for k in range(0, 150, 30):
        p.insert(rows(spark, cells[k : k + 30]))
    before = sorted(map(str, p.bricks().collect()))
    p.compact()
    assert p.commits == [3, 4] and sorted(map(str, p.bricks().collect())) == before
    assert pool.open_pool(spark, vm, p.path).commits == [3, 4]
    p.insert(rows(spark, cells[120:]), 4)
    assert sorted(map(str, p.bricks().collect())) == before


def test_stream_goes_on_from_its_checkpoint(spark, tmp_path):
    cells = scan_table(spark, tmp_path, [n % 40 for n in range(200)])
    vm = grid.VolumeMeta("scan", (40, 100, 30), (8, 8, 8), 3)
    files = stream_ingest.slice_batches(spark, str(tmp_path), 3)
    p, seen = pool.BrickPool.create(spark, vm), []

    def fail_at_four(version):
        seen.append(version)
        if version == 4:
            raise RuntimeError("the driver is lost")

    with pytest.raises(Exception, match="the driver is lost"):
        stream_ingest.stream_build(p, files, fail_at_four, str(tmp_path / "state"), compact_every=2)
    again = pool.open_pool(spark, vm, p.path)
    stream_ingest.stream_build(again, files, seen.append, str(tmp_path / "state"), compact_every=2)
    assert seen == [0, 1, 2, 3, 4, 4, 5, 6, 7, 8, 9]  # the batch that failed comes again
    want = collections.Counter()
    for x, y, z, v in cells:
        want[x, y, z, 0, v] += 1
    assert collections.Counter((r.x, r.y, r.z, r.c, r.v) for r in again.voxels(level=0).collect()) == want


def test_plans_do_not_grow_with_the_levels(spark, volume):
    """The bricks of a version are read from files: their plan is a scan, whatever the depth."""
    vm, cells = volume
    size = []
    for brick in ((8, 8, 8), (2, 2, 2)):
        p = pool.BrickPool.create(spark, vm.with_brick(*brick))
        p.insert(rows(spark, cells[:80]))
        p.insert(rows(spark, cells[80:]))
        size.append(len(p.bricks()._jdf.queryExecution().optimizedPlan().toString()))
    assert size[1] < 1.1 * size[0]


@pytest.mark.parametrize("way", ["channel", "octant", "none"])
def test_builders_give_the_same_bricks(spark, volume, way):
    vm, cells = volume
    cols = ["level", "key", "n", "body", "known", "bmin", "bmax", "bsum", "smin", "smax"]
    got = [sorted(map(str, ingest.build(rows(spark, cells), vm, k).bricks().select(cols).collect())) for k in ("shards", way)]
    assert got[0] == got[1]


@pytest.mark.parametrize("way", ["none", "octant"])
def test_lone_builders_work_in_bounded_groups(spark, monkeypatch, way):
    vm, climb = grid.VolumeMeta("long", (64, 2, 2), (2, 2, 2)), pool._climb

    def bounded(*args):
        run = climb(*args)

        def each(table):
            if table.num_rows > 8:
                raise ValueError(f"{table.num_rows} rows in a group")
            return run(table)

        return each

    monkeypatch.setattr(pool, "_climb", bounded)
    monkeypatch.setattr(pool, "GROUP_VOXELS", 64)  # a brick and its children
    built = ingest.build(rows(spark, [(x, 0, 0, 0, x + 1) for x in range(64)]), vm, way)
    assert {r.level: r["count"] for r in built.bricks().groupBy("level").count().collect()} == {l: 32 >> l for l in range(6)}


def test_eager_pruning_follows_the_worked_example_and_depends_on_the_order(spark):
    vm = more_queries.LINE

    def grow(order, threshold):
        tree, states = eager.empty_tree(spark, vm), []
        for k in order:
            x0, values = more_queries.LINE_BLOCKS[k]
            tree = eager.insert_eager(tree, rows(spark, [(x0 + i, 0, 0, 0, v) for i, v in enumerate(values)]), vm, threshold)
            states.append({(r.level, r.ix): (r.avg[0], r.body is not None, r.children) for r in tree.filter("iy = 0 and iz = 0").collect()})
        return states

    one = grow(range(4), 1)
    # all children of a node exist at once, without bricks
    assert one[0][0, 1] == (0, False, False) and one[0][1, 1] == (0, False, False)
    # after the third block two bricks are only averages, but the left subtree stays
    assert one[2][0, 1] == (3, False, False) and one[2][1, 0] == (3, False, True) and one[2][0, 0] == (3, True, False)
    # after the fourth the root is homogeneous, and no subtree goes
    assert one[3][2, 0] == (3, False, True) and len(one[3]) == 7
    lossy = {str(sorted(grow(order, 4)[-1].items())) for order in ((0, 1, 2, 3), (2, 3, 0, 1))}
    assert len(lossy) == 2


def test_an_opaque_sample_hides_what_lies_behind(spark):
    two = spark.createDataFrame([(0, 0, 0, 0, 1.0, 0.0, 0.0, 1.0), (0, 0, 1, 1, 0.0, 1.0, 0.0, 0.5)], "px int, py int, i int, c int, r double, g double, b double, a double")
    forms = [raycast.dvr_window(two), raycast.dvr_fold(two), raycast.dvr_segments(two, 1), raycast.dvr_segments(two, 8), filtering.intermix(two, "accumulation"), filtering.intermix(two, "sample")]
    for f in forms:
        r = f.first()
        assert (r.r, r.g, r.b, r.a) == (1.0, 0.0, 0.0, 1.0)
    image, spent = raycast.dvr_wavefront([lambda going, k=k: two.filter(f"i = {k}").join(going, ["px", "py"]) for k in (0, 1)], two.select("px", "py"), 0.95, storage.keep)
    assert image.first().g == 0 and spent == [(1, 1), (0, 0)]


def test_transfer_tables_are_linear_in_segments(spark):
    cells = spark.createDataFrame([(0, 5), (0, 15), (1, 5), (0, 40)], "c int, v long")
    got = {(r.c, r.v): (r.r, r.a) for r in raycast.transfer_table(cells, [(0, 0, 10, 0, 0, 0, 0, 1, 0, 0, 0.5), (0, 10, 20, 1, 0, 0, 0.5, 0, 0, 0, 1)]).collect()}
    assert got == {(0, 5): (0.5, 0.25), (0, 15): (0.5, 0.75)}


def test_wide_entries_round_trip(spark):
    few = spark.createDataFrame([(1.5, 0.0, 40000.25)], "a double, b double, c double")
    entry = codec.encode_wide(F.lit(True), F.lit(False), F.lit(77), [F.col(k) for k in "abc"])
    r = few.select(entry.alias("e")).select(*codec.decode_wide(F.col("e"), 3), *codec.decode_node(F.col("e.lo")).values()).first()
    assert tuple(r[:3]) == (1.5, 0.0, 40000.25) and (r[3], r[4], r[5]) == (1, 0, 77)
    many = spark.createDataFrame([(65535, 1, 0, 40000, 7, 65534)], "a long, b long, c long, d long, e long, f long")
    entry = codec.encode_wide(F.lit(False), F.lit(True), F.lit(5), [F.col(k) for k in "abcdef"])
    assert tuple(many.select(entry.alias("w")).select(*codec.decode_wide(F.col("w"), 6)).first()) == (65535, 1, 0, 40000, 7, 65534)


def test_node_buffer_loads_and_unloads(spark):
    words = spark.createDataFrame([(0, 2 | 9 << 24), (1, 2 | 8 << 24)], "idx long, word long")
    averages = spark.createDataFrame([(0, 9), (1, 8)], "idx long, payload long")
    slots = lambda *s: spark.createDataFrame(list(s), "idx long, slot long")
    first = node_buffer.load(words, slots((0, 4)), averages)
    assert {r.idx: r.word for r in first.collect()} == {0: 3 | 4 << 24, 1: 2 | 8 << 24}
    assert {r.idx: r.word for r in node_buffer.load(first, slots((1, 0)), averages).collect()} == {0: 2 | 9 << 24, 1: 3}


def test_passes_with_uploads_end_and_stay_within_the_slots(spark, volume):
    vm, cells = volume
    p = pool.BrickPool.create(spark, vm)
    p.insert(rows(spark, cells))
    nodes = octree.nodes_of_bricks(p.bricks(), vm, 0)
    view = camera.Camera((-9.0, 5.0, -9.0), (4.0, 3.0, 2.0), width=6, height=6)
    samples = camera.choose_level(camera.sample_perspective(camera.perspective_rays(spark, view, vm), vm, 1.0), view, vm)
    resolved, passes = render.run_passes(samples, nodes, vm.top, 500, storage.keep)
    assert passes[-1]["uploads"] == 0 and set(passes[-1]["kinds"]) <= {"self", "homogeneous"}
    _, few = render.run_passes(samples, nodes, vm.top, 3, storage.keep, most=4)
    assert all(q["slots"] <= 3 for q in few)
    _, fifo = render.run_passes(samples, nodes, vm.top, 3, storage.keep, mode="basic", policy="fifo", most=4)
    assert all(q["slots"] <= 3 and q["evictions"] == 0 for q in fifo)
    averages = p.stats().join(p.bricks().select("level", "ix", "iy", "iz", "key"), ["level", "ix", "iy", "iz"]).select("level", "key", "c", "avg")
    whole = {(r.px, r.py, r.c): r.v for r in render.image(render.fetch(resolved, p.bricks(), averages, vm), "mip", None).collect()}
    direct = render.resolve(samples, nodes, nodes.select("level", "key").limit(0), "direct")
    assert whole == {(r.px, r.py, r.c): r.v for r in render.image(render.fetch(direct, p.bricks(), averages, vm), "mip", None).collect()}
    assert render.tile(samples, 3).select("tx", "ty").distinct().count() <= 4
    with pytest.raises(ValueError):
        render.resolve(samples, nodes, nodes, "other")


def test_resampled_channel_equals_sampling_through_the_matrix(spark, volume):
    vm, cells = volume
    for m in (aberration.scaling(1.3), aberration.compose(aberration.translation(0, 6, 0), aberration.rotation(-90)), aberration.translation(1, 0, -1)):
        copied = {tuple(r[:3]): r[4] for r in aberration.resample_channel(rows(spark, cells), 1, m, vm).filter("c = 1").collect()}
        source = {tuple(c[:3]): c[4] for c in cells if c[3] == 1}
        want = {}
        for at in itertools.product(*map(range, vm.dims)):
            to = tuple(math.floor(sum(m[k][j] * (at[j] + 0.5) for j in range(3)) + m[k][3]) for k in range(3))
            if to in source:
                want[at] = source[to]
        assert copied == want
    whole = aberration.compose(m, aberration.inverse(m))
    assert np.allclose(whole, aberration.identity())


def test_raw_stack_round_trip(spark, volume, tmp_path):
    vm, cells = volume
    a = dense(vm, cells)
    for z in range(vm.dims[2]):
        for c in range(vm.channels):
            raw_stack.write_slice(str(tmp_path), c, z, a[:, :, z, c].T)
    got = raw_stack.read_stack(spark, str(tmp_path), vm.dims[0])
    assert sorted(map(tuple, got.select(*"xyzcv").collect())) == sorted(cells)
    assert raw_stack.read_stack(spark, str(tmp_path), vm.dims[0], z=2, c=1).count() == sum(c[2] == 2 and c[3] == 1 for c in cells)
    image = spark.createDataFrame([(0, 0, 1.0, 0.0, 0.5), (1, 1, 0.0, 2.0, 0.0)], "px int, py int, r double, g double, b double")
    raw_stack.write_image(image, str(tmp_path / "i.ppm"), 2, 2)
    assert (tmp_path / "i.ppm").read_bytes() == b"P6 2 2 255\n" + bytes([255, 0, 128, 0, 0, 0, 0, 0, 0, 0, 255, 0])


def test_as_of_and_box_joins(spark, volume):
    vm, cells = volume
    rng = random.Random(9)
    left, right = ([(rng.randrange(3), rng.randrange(20)) for _ in range(30)] for _ in range(2))
    r = spark.createDataFrame([(k, t, i) for i, (k, t) in enumerate(sorted(set(right)))], "k int, t int, value int")
    got = {(x.k, x.t): x.value for x in relations.as_of(spark.createDataFrame(left, "k int, t int"), r, "k", "t", "value").collect()}
    at = [(x.k, x.t, x.value) for x in r.collect()]
    assert got == {(k, t): max(((u, v) for j, u, v in at if j == k and u <= t), default=(0, None))[1] for k, t in left}
    p = pool.BrickPool.create(spark, vm)
    p.insert(rows(spark, cells))
    boxes = [(b, *(lo := [rng.randrange(d) for d in vm.dims]), *(min(d - 1, x + rng.randrange(6)) for x, d in zip(lo, vm.dims))) for b in range(8)]
    found = relations.bricks_in_boxes(p.bricks(), spark.createDataFrame(boxes, "box int, x0 int, y0 int, z0 int, x1 int, y1 int, z1 int"), vm, 0)
    held = {(c[0] // 2, c[1] // 2, c[2] // 2) for c in cells}
    want = {(b[0], *h) for b in boxes for h in held if all(2 * h[k] <= b[4 + k] and 2 * h[k] + 1 >= b[1 + k] for k in range(3))}
    assert {(r.box, r.ix, r.iy, r.iz) for r in found.collect()} == want


def test_borders_of_all_levels_and_filtering_across_levels(spark, volume):
    vm, cells = volume
    p = pool.BrickPool.create(spark, vm)
    p.insert(rows(spark, cells))
    held = collections.defaultdict(set)
    for r in borders.border_job(p).collect():
        held[r.level].add((r.ix, r.iy, r.iz, r.x, r.y, r.z, r.c, r.v))
    for level in range(vm.top + 1):
        dims, want = vm.at_level(level), set()
        for r in p.voxels(level=level).collect():
            for step in itertools.product((-1, 0, 1), repeat=3):
                at = [v + d for v, d in zip((r.x, r.y, r.z), step)]
                if all(0 <= a < -(-d // 2) * 2 for a, d in zip(at, dims)) and (brick := tuple(a // 2 for a in at)) != (r.x // 2, r.y // 2, r.z // 2):
                    want.add((*brick, r.x, r.y, r.z, r.c, r.v))
        assert held[level] == want
    samples = spark.createDataFrame([(i, 0, i, 2 * i, i, i, 0.25, 0.0, 0.5, f) for i, f in enumerate((0.0, 0.5, 1.0, 0.25))], "px int, py int, i int, x int, y int, z int, fx double, fy double, fz double, f double")
    fine = dense(vm, cells)
    coarse = half(fine)

    def lookup(a, place, c):
        low = [math.floor(v) for v in place]
        total = 0.0
        for o in itertools.product((0, 1), repeat=3):
            at = [v + k for v, k in zip(low, o)]
            w = math.prod((v - b) if k else 1 - (v - b) for v, b, k in zip(place, low, o))
            total += w * a[(*at, c)] if all(v < d for v, d in zip(at, a.shape)) else 0.0
        return total

    got = {(r.px, r.c): r.v for r in borders.cross_level(samples, p).collect()}
    for i, f in enumerate((0.0, 0.5, 1.0, 0.25)):
        place = (2 * i + 0.25, float(i), i + 0.5)
        for c in range(2):
            want = (1 - f) * lookup(fine, place, c) + f * lookup(coarse, [max(0.0, (v + 0.5) / 2 - 0.5) for v in place], c)
            assert got.get((i, c), 0) == pytest.approx(want)


def test_viewer_goes_from_full_frames_to_refinement_and_back(spark, volume, tmp_path):
    vm, cells = volume
    p = pool.BrickPool.create(spark, vm)
    p.insert(rows(spark, cells))
    nodes = octree.nodes_of_bricks(p.bricks(), vm, 0)
    averages = p.stats().join(p.bricks().select("level", "ix", "iy", "iz", "key"), ["level", "ix", "iy", "iz"]).select("level", "key", "c", "avg")
    viewer = session.Viewer(p, nodes, averages, lambda f: raycast.transfer(f, 100), 500, str(tmp_path / "images"))
    assert viewer.shown() is None
    viewer.look(camera.Camera((-9.0, 5.0, -9.0), (4.0, 3.0, 2.0), width=5, height=5))
    first = viewer.step()
    assert first["mode"] == "full_frame" and first["requests"] > 0 and viewer.shown() is not None
    last = viewer.step()
    assert last["mode"] == "refine" and viewer.session.mode == "done"
    samples = viewer.samples()
    direct = render.fetch(render.resolve(samples, nodes, nodes.limit(0).select("level", "key"), "direct"), p.bricks(), averages, vm)
    want = {(r.px, r.py): r.a for r in raycast.dvr_window(raycast.transfer(direct, 100)).collect()}
    assert {(r.px, r.py): r.a for r in viewer.shown().collect()} == pytest.approx(want)
    viewer.clip([(1, 0, 0, -4.0)])
    assert viewer.session.mode == "full_frame" and viewer.samples().filter("x < 4").count() == 0
    viewer.set_matrix(1, aberration.translation(50, 0, 0))  # the channel is moved out of the volume
    viewer.step()
    assert viewer.fetched(viewer.samples(), render.resolve(viewer.samples(), nodes, viewer.resident)).filter("c = 1").count() == 0


def test_gallery(spark, tmp_path):
    for path in experiments.gallery(spark, SF, str(tmp_path), 8):
        with open(path, "rb") as f:
            assert f.read(11) == b"P6 8 8 255\n" and any(f.read())


def test_experiments_run(spark):
    built = experiments.run_build(spark, SF, "ribbon")
    assert built["bricks"] == 110 and 0 < built["pool_over_data"] < 2
    turned = experiments.run_rotation(spark, SF, "ribbon", frames=2, pixels=6, slots=16, projection="mip")
    assert turned["frames"] == 2 and abs(sum(turned["sources"].values()) - 1) < 0.01
    few, many = (experiments.run_refinement(spark, SF, "ribbon", slots=k, pixels=6) for k in (1, 500))
    assert few["passes"] >= max(few["needed"], many["passes"]) and few["needed"] == many["needed"] <= min(few["uploads"], many["uploads"])
    capped = experiments.run_refinement(spark, SF, "ribbon", slots=500, pixels=6, cap_pages=1)
    assert capped["page_switches"] >= many["page_switches"]


def test_memory_guard_and_thresholds_per_channel(spark, volume):
    vm, cells = volume
    with pytest.raises(MemoryError):
        experiments.guarded_bruteforce(rows(spark, cells), vm, None, 100)
    p = pool.BrickPool.create(spark, vm)
    p.insert(rows(spark, cells))
    none, both = (octree.nodes_of_bricks(p.bricks(), vm, t).filter("homog").count() for t in ([0.0, 1000.0], [1000.0, 1000.0]))
    assert none == 0 and both == p.bricks().count()


def test_expected_brick_counts(spark):
    """Independent counts of the sparse volume: bricks with voxels, absent ones added in closed form."""
    v, vm = open_volume(spark, SF, "ribbon")
    nodes = octree.build_nodes(mipmap.pyramid_stats(v, vm), vm, 25.6)
    got = {r.level: (r.bricks, r.homogeneous, r.subtrees) for r in octree.level_summary(nodes).collect()}
    whole = {}
    for level, (n, h, s) in got.items():
        bx, by, bz = vm.bricks_at(level)
        absent = bx * by * bz - n
        whole[level] = (n + absent, h + absent, s + absent)
    assert whole == {0: (144, 70, 70), 1: (40, 16, 16), 2: (12, 4, 4), 3: (4, 2, 1), 4: (1, 0, 0)}


def test_three_compositing_forms_agree(spark):
    rng = random.Random(3)
    samples = spark.createDataFrame([(p, 0, i, c, rng.randrange(1, 60000)) for p in range(5) for i in range(20) for c in range(3)], "px int, py int, i int, c int, v long")
    shaded = raycast.transfer(samples, 65535)
    forms = [raycast.dvr_window(shaded), raycast.dvr_fold(shaded), raycast.dvr_segments(shaded, 6)]
    images = [{r.px: (r.r, r.g, r.b, r.a) for r in f.collect()} for f in forms]
    for p in range(5):
        for other in images[1:]:
            assert all(math.isclose(a, b, abs_tol=1e-9) for a, b in zip(images[0][p], other[p], strict=True))


def test_node_word_round_trip(spark):
    df = spark.createDataFrame([(True, False, 0, 5), (False, True, (1 << 22) - 1, (1 << 40) - 1), (True, True, 7, 0)], "b boolean, h boolean, g long, p long")
    word = codec.encode_node(F.col("b"), F.col("h"), F.col("g"), F.col("p"))
    got = df.select("b", "h", "g", "p", *(c.alias(k) for k, c in codec.decode_node(word).items())).collect()
    assert all((int(r.b), int(r.h), r.g, r.p) == (r.in_buffer, r.has_brick, r.child_group, r.payload) for r in got)


def test_lru_by_distance_equals_simulation(spark):
    rng = random.Random(8)
    trace = spark.createDataFrame([(k, s, rng.randrange(12), False, False, False) for k in range(3) for s in range(80)], "cache long, seq long, page long, write boolean, pin boolean, unpin boolean")
    hits = {(r.cache, r.seq): r.hit for r in paging.simulate_lru(trace, 5).collect()}
    for r in paging.stack_distances(trace.select("cache", "seq", "page")).collect():
        assert hits[r.cache, r.seq] == int(r.distance is not None and r.distance < 5)


def test_pinned_pages_block(spark):
    t = [(0, 0, 1, False, True, False), (0, 1, 2, True, True, False), (0, 2, 3, False, False, False), (0, 3, 2, False, False, True), (0, 4, 3, False, False, False)]
    got = paging.simulate_lru(spark.createDataFrame(t, "cache long, seq long, page long, write boolean, pin boolean, unpin boolean"), 2).orderBy("seq").collect()
    assert [r.blocked for r in got] == [0, 0, 1, 0, 0] and got[4].evicted == 2 and got[4].written == 1


def test_refinement_ends_and_loads_every_brick(spark):
    samples = spark.createDataFrame([(p, 0, i, (i * 3 + p) % 11) for p in range(4) for i in range(9)], "px int, py int, i int, key long").cache()
    bricks = samples.select("key").distinct().count()
    passes, uploads = fullframe.refine(samples, 2, storage.keep)
    assert passes >= -(-bricks // 2) and uploads >= bricks


def test_delta_equals_rebuild(spark):
    a = spark.createDataFrame([(1, 5), (2, 6), (3, 7)], "k int, w int")
    b = spark.createDataFrame([(1, 5), (2, 8), (4, 9)], "k int, w int")
    d = paging.diff_versions(a, b, ["k"], "w")
    assert {(r.k, r.kind) for r in d.collect()} == {(2, "update"), (3, "delete"), (4, "create")}
    assert sorted(map(tuple, paging.apply_delta(a, d, ["k"], "w").collect())) == [(1, 5), (2, 8), (4, 9)]


def test_overlapping_bricks_filter_like_the_whole_volume(spark, volume):
    vm, cells = volume
    rng = random.Random(6)
    places = [(i, 0, i, rng.randrange(8), rng.randrange(6), rng.randrange(4), *(rng.randrange(4) / 4 for _ in range(3))) for i in range(40)]
    samples = spark.createDataFrame(places, "px int, py int, i int, x int, y int, z int, fx double, fy double, fz double")
    a = dense(vm, cells)
    got = {}
    for border in ("global", "overlap"):
        got[border] = {(r.px, r.c): r.v for r in filtering.trilinear(samples, rows(spark, cells), vm, border).collect()}
    assert got["global"] == pytest.approx(got["overlap"])
    for px, _, _, x, y, z, fx, fy, fz in places:
        for c in range(2):
            want = sum(a[x + p, y + q, z + r, c] * (fx if p else 1 - fx) * (fy if q else 1 - fy) * (fz if r else 1 - fz) for p, q, r in itertools.product((0, 1), repeat=3))
            assert got["global"].get((px, c), 0) == pytest.approx(want)
    with pytest.raises(ValueError):
        filtering.trilinear(samples, rows(spark, cells), vm, "none")


def test_haar_details_of_constant_and_checkerboard(spark):
    flat = rows(spark, [(x, y, z, 0, 5) for x, y, z in itertools.product(range(4), repeat=3)])
    assert {r.level: r.details for r in filtering.haar_sizes(flat, 2).collect()} == {0: 0, 1: 0}
    board = rows(spark, [(x, y, z, 0, 8 * ((x + y + z) % 2)) for x, y, z in itertools.product(range(4), repeat=3)])
    assert {r.level: r.details for r in filtering.haar_sizes(board, 2).collect()} == {0: 8, 1: 0}


def test_everything_resident_needs_no_substitute(spark, volume):
    vm, cells = volume
    stats = mipmap.pyramid_stats(rows(spark, cells), vm)
    nodes = octree.build_nodes(stats, vm, 0)
    view = camera.Camera((-9.0, 5.0, -9.0), (4.0, 3.0, 2.0), width=6, height=6)
    samples = camera.choose_level(camera.sample_perspective(camera.perspective_rays(spark, view, vm), vm, 1.0), view, vm)
    whole = camera.resolve_at(samples, nodes, nodes.select("level", "key")).collect()
    assert whole and all(r.up in (0, 3) and not r.asks for r in whole)
    none = camera.resolve_at(samples, nodes, nodes.select("level", "key").filter("false")).collect()
    assert all(r.up == 3 for r in none) and any(r.asks for r in none) and len(none) == len(whole)
    assert len(camera.turn((4, 3, 2), 20.0, 4)) == 4


def test_session_refines_at_rest_and_falls_back_on_moves():
    s = session.RenderSession()
    assert s.step("idle") == "full_frame"
    assert s.step("pass_done", image=1, requests=5) == "full_frame" and s.shown == 1
    assert s.step("idle") == "refine"
    assert s.step("pass_done", image=2, requests=3) == "refine" and s.shown == 1
    assert s.step("pass_done", image=3, requests=0) == "done" and s.shown == 3
    assert s.step("channel_matrix", channel=1, matrix="m") == "full_frame" and s.matrices == {1: "m"}
    with pytest.raises(ValueError):
        s.step("nothing")


def interleaved(x, y, z):
    return sum((x >> i & 1) << 3 * i | (y >> i & 1) << 3 * i + 1 | (z >> i & 1) << 3 * i + 2 for i in range(21))


def scan_table(spark, path, users):
    """An events table with one view a row, and its voxels as x, y, z, v."""
    import datetime
    import json

    cells = [(u, n * 11 % 100, n * 7 % 30, 100 * (n + 1)) for n, u in enumerate(users)]
    start = datetime.datetime(2024, 1, 1)
    data = [(n, start + datetime.timedelta(hours=6 * z), x, "view", v / 100, json.dumps({"k": y})) for n, (x, y, z, v) in enumerate(cells)]
    spark.createDataFrame(data, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").write.parquet(f"{path}/events.parquet")
    return cells


def test_depth_of_the_queries_follows_the_volume(spark, tmp_path):
    """Bricks 32 apart along an axis share the last five octal digits of their keys."""
    cells = scan_table(spark, tmp_path, [3, 3 + 8 * 32, 3 + 8 * 64, 700, 1499])
    got = lambda name: registry.QUERIES[name](spark, str(tmp_path)).collect()
    keys = [(interleaved(x // 8, y // 8, z // 8), v) for x, y, z, v in cells]
    assert {(r.key, r.path) for r in got("node_path_octal")} == {(k, f"{k:08o}") for k, _ in keys}
    want = {(l, k >> 3 * l): [v for other, v in keys if other >> 3 * l == k >> 3 * l] for k, _ in keys for l in range(9)}
    assert {(r.level, r.key): (r.lo, r.hi, r.s, r.cnt) for r in got("octree_rollup_stats")} == {k: (min(v), max(v), sum(v), len(v)) for k, v in want.items()}
    assert {r.level: r.nodes for r in got("recursive_ancestors")} == {l: len({k >> 3 * l for k, _ in keys}) for l in range(9)}


def test_keys_beyond_1024_bricks(spark, tmp_path):
    cells = scan_table(spark, tmp_path, [5, 8192 + 5, 2 * 8192 + 5, 150_000])
    want = {(x // 8, y // 8, z // 8): interleaved(x // 8, y // 8, z // 8) for x, y, z, _ in cells}
    assert {(r.ix, r.iy, r.iz): r.key for r in registry.QUERIES["morton_encode"](spark, str(tmp_path)).collect()} == want
    assert {(r.ix, r.iy, r.iz): r.key for r in registry.QUERIES["morton_decode"](spark, str(tmp_path)).collect()} == want
    # bricks 0 and 1 with their parent are homogeneous, 1024 and 1025 with theirs are not: neither may hide the other
    vm = grid.VolumeMeta("long", (4096, 1, 1), (2, 2, 2))
    spikes = [(x, 0, 0, 0, 9) for x in (0, 1, 2, 3)] + [(2048 + x, 0, 0, 0, 9) for x in (0, 3)]
    stats = spark.createDataFrame([(l, x >> l + 1, 0, 0, 0, 2, 9 * (l == 0), 9, 9 * (x < 4), 9, 9) for l in (0, 1) for x in (0, 2, 2048, 2050) if l == 0 or x % 4 == 0], "level int, ix int, iy int, iz int, c int, n long, bmin long, bmax long, smin long, smax long, avg long")
    kept = {(r.level, r.key) for r in octree.collapse(octree.build_nodes(stats, vm, 5), vm).collect()}
    assert kept == {(1, 0), (1, interleaved(512, 0, 0)), (0, interleaved(1024, 0, 0)), (0, interleaved(1025, 0, 0))}
    assert mipmap.pack_bricks(rows(spark, spikes), vm, 0).select("key").distinct().count() == 4


def test_a_coordinate_that_does_not_fit_is_an_error(spark):
    for x, bits in ((1 << 21, 21), (8, 3), (-1, 21)):
        with pytest.raises(Exception, match="brick coordinate beyond"):
            spark.createDataFrame([(x,)], "x int").select(grid.morton3(F.col("x"), F.lit(0), F.lit(0), bits)).collect()
    with pytest.raises(ValueError):
        grid.morton3(F.lit(0), F.lit(0), F.lit(0), 22)


def test_last_views_cover_the_whole_table(spark, tmp_path):
    cells = scan_table(spark, tmp_path, [n % 40 for n in range(600)])
    last = {x: (n, v) for n, (x, _, _, v) in enumerate(cells)}
    assert {r.user_id: (r.last_view, r.v) for r in registry.QUERIES["asof_last_slice"](spark, str(tmp_path)).collect()} == last


def test_full_buffer_of_a_wide_volume_is_counted_without_its_empty_words(spark, tmp_path):
    """A user far out makes a complete tree of 10 ** 13 words, all but a few of them 0."""
    scan_table(spark, tmp_path, [3, 200_000])
    (r,) = registry.QUERIES["node_buffer_full"](spark, str(tmp_path)).collect()
    idx = [k.idx for k in queries.words(spark, str(tmp_path)).collect()]
    assert (r.words, r.filled, r.position_sum) == (grid.bfs_base(16), len(idx), sum(idx))


def test_ancestors_are_not_bounded_by_the_recursion_limit(spark, tmp_path):
    cells = scan_table(spark, tmp_path, [8 * n for n in range(40)])
    keys = [interleaved(x // 8, y // 8, z // 8) for x, y, z, _ in cells]
    spark.conf.set("spark.sql.cteRecursionRowLimit", 39)
    try:
        got = {r.level: r.nodes for r in registry.QUERIES["recursive_ancestors"](spark, str(tmp_path)).collect()}
    finally:
        spark.conf.unset("spark.sql.cteRecursionRowLimit")
    assert got == {l: len({k >> 3 * l for k in keys}) for l in range(7)}


def agrees(spark, sf_dir, name):
    """Rows of a query and of its oracle over the tables of a directory, columns by name."""
    import glob
    import os

    import duckdb

    con = duckdb.connect()
    for f in glob.glob(f"{sf_dir}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}{'/*.parquet' if os.path.isdir(f) else ''}'")
    got = registry.QUERIES[name](spark, str(sf_dir))
    columns = ", ".join(sorted(got.columns))
    return sorted(map(tuple, got.select(*sorted(got.columns)).collect())), sorted(con.sql(f"SELECT {columns} FROM ({registry.ORACLES[name]}) AS q").fetchall())


@pytest.mark.parametrize("name", ["base_rebuild_words", "delta_events", "delta_apply_equals_rebuild"])
def test_words_of_a_tree_beyond_the_pointer_follow_the_sql(spark, tmp_path, name):
    """Eleven levels: breadth-first numbers have more bits than a word's pointer."""
    scan_table(spark, tmp_path, [7 * n for n in range(30)] + [8999 - n for n in range(30)])
    got, want = agrees(spark, tmp_path, name)
    assert want and got == want


@pytest.mark.parametrize("name", ["delta_apply_equals_rebuild", "delta_events"])
def test_words_whose_fields_meet_follow_the_sql(spark, tmp_path, name):
    """Nodes above the leaves whose averages share bits with a pointer that is too long: there a sum is not an OR."""
    scan_table(spark, tmp_path, [8999 - n % 16 for n in range(300)])
    got, want = agrees(spark, tmp_path, name)
    low = (1 << codec.POINTER_BITS) - 1
    inner = [(r[0] + 1, r[-1]) for r in want if r[-1] and r[-1] >> 2 & low == r[0] + 1 & low]
    assert any(word - (group << 2) >> 2 + codec.POINTER_BITS & group >> codec.POINTER_BITS for group, word in inner)
    assert got == want


def test_words_counted_by_level_are_those_of_the_full_buffer(spark, volume):
    vm, cells = volume
    kept = octree.collapse(octree.build_nodes(mipmap.pyramid_stats(rows(spark, cells), vm), vm, 20), vm)
    words = node_buffer.node_words(kept, vm)
    every = node_buffer.full(words, vm).agg(F.count("*"), F.bit_xor("word")).first()
    counts = node_buffer.level_counts(words, vm).agg(F.sum("words"), F.sum("nodes")).first()
    assert (counts[0], words.agg(F.bit_xor("word")).first()[0]) == tuple(every) and counts[1] == kept.count()


@pytest.mark.parametrize("slots", [2, 50])
def test_refined_image_equals_the_direct_one(spark, slots):
    """Also with several channels a place, bricks met again later on a ray, and rays that end at different passes."""
    rng = random.Random(5)
    cells = [(p, 0, i, c, rng.randrange(1, 60000), (i // 2 * 3 + p) % 7) for p in range(4) for i in range(2 + 3 * p) for c in range(1 + i % 2)]
    shaded = raycast.transfer(spark.createDataFrame(cells, "px int, py int, i int, c int, v long, key long"), 65535)
    image, passes, uploads = fullframe.refine_image(shaded, slots, storage.keep)
    bricks = len({c[5] for c in cells})
    assert passes >= -(-bricks // slots) and uploads >= bricks
    projected, mip_passes, _ = fullframe.refine_mip(shaded, slots, storage.keep)
    assert mip_passes == passes and sorted(map(tuple, projected.collect())) == sorted(map(tuple, raycast.mip_image(shaded).collect()))
    want = {r.px: r for r in raycast.dvr_window(shaded).collect()}
    got = {r.px: r for r in image.collect()}
    assert set(got) == set(want) and all(r.samples == want[k].samples for k, r in got.items())
    assert all(math.isclose(r[f], want[k][f], abs_tol=1e-9) for k, r in got.items() for f in "rgba")


ORACLED = [
    "perspective_rays", "optimal_lod", "metric_lod_histogram", "full_frame_image", "metric_image_error", "trilinear_sample", "trilinear_halo_equals_global", "trilinear_clamped",
    "base_neighbour_fetch_count", "intermix_image_level", "intermix_sample_level", "base_haar_bytes", "metric_requests_per_pass", "metric_slot_occupancy", "metric_traversal_steps",
    "incr_insert_sequence", "incr_batch_equals_sequence", "worked_example_states", "delta_events", "residency_patch", "tier_of_request", "dirty_writebacks", "sample_source_kind", "used_and_requested", "full_frame_dvr", "dvr_wavefront",
    "dvr_opaque_segments", "box_overlap_join", "asof_event_view", "stream_session_runs", "sqludf_morton", "udtf_octant_children", "deferred_borders", "eager_border_updates", "sparse_channel_pack", "error_lod", "octree_rollup_stats", "recursive_ancestors",
    "octree_collapsed_scan", "mip_all_levels_sales", "dvr_window_scan", "full_frame_fallback", "halo_bricks", "stream_tumbling_slices", "incr_overwrite", "worked_example_1d"]


@pytest.mark.parametrize("name", ORACLED)
def test_query_equals_oracle(spark, name):
    import glob
    import os

    import duckdb

    con = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    got = registry.QUERIES[name](spark, SF)
    want = con.sql(registry.ORACLES[name])
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)

    def plain(data):
        return sorted((tuple(v if v is None or isinstance(v, str) else round(float(v), 6) for v in r) for r in data), key=str)

    assert plain(got.select(columns).collect()) == plain(con.sql(f"SELECT {', '.join(columns)} FROM ({registry.ORACLES[name]}) AS q").fetchall())


@pytest.mark.parametrize("name", ["addressing_limits", "base_neighbour_fetch_count", "grid_fit", "grid_fit_aniso", "halo_overhead", "halo_one_sided_overhead", "math_lod_table", "metric_data_size_ribbon", "metric_data_size_scan", "metric_mip_overhead", "node_buffer_size"])
def test_measures_of_a_table_are_read_by_tasks(spark, name):
    """The plan scans the table, and the result is the oracle's."""
    got, want = agrees(spark, SF, name)
    assert want and got == want
    assert "parquet" in registry.QUERIES[name](spark, SF)._jdf.queryExecution().optimizedPlan().collectLeaves().mkString(" ").lower()


def test_every_query_has_an_oracle():
    assert set(registry.QUERIES) == set(registry.ORACLES)
    assert reduce(lambda n, q: n + 1, registry.QUERIES, 0) > 120
    assert isinstance(queries.QUERIES, dict) and DataFrame
