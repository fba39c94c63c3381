"""The brick pool: versions of dense bricks by level and key in the shared folder, built block by block.

A pool is a folder of Parquet versions, each partitioned by level and sorted by Morton key.  A block
of voxels makes one version that holds the rewritten bricks only: its leaf bricks and their
ancestors.  Bodies hold null where nothing has been inserted; such voxels count as background.
What a version needs of the pool is known in closed form from the block's leaf bricks: their old
bodies, and the untouched siblings on the way to the root.  Bricks are grouped by an ancestor a few
levels up, and all levels below it are half-sampled in that group, so a build of N levels takes
N / height steps, whatever the number of blocks before.

``canonical`` pools keep all bodies and prune as a view (``octree.collapse``), so any order of
blocks gives the same tree.  ``eager`` pools delete homogeneous bricks and subtrees at each
insertion and go on from their averages, which loses detail and depends on the order; their groups
span the whole tree, so they are for small volumes.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import storage
from ..functions.grid import AXES, VolumeMeta, coords, morton3

STATS = ("known", "bmin", "bmax", "bsum", "smin", "smax")
SCHEMA = "level int, key long, ix int, iy int, iz int, n long, body array<int>, " + ", ".join(f"{s} array<long>" for s in STATS)
#: Voxels that meet in one group while levels are half-sampled.
GROUP_VOXELS = 1 << 22
#: Marks a version whose levels are all written.
DONE = "_COMMITTED"


def group_height(vm: VolumeMeta) -> int:
    """How many levels are half-sampled in one group: as many as keep its bricks within ``GROUP_VOXELS``."""
    cells = vm.brick[0] * vm.brick[1] * vm.brick[2] * vm.channels
    height = 1
    while height < vm.top and cells * 8 ** (height + 1) <= GROUP_VOXELS:
        height += 1
    return height


# --- bricks as arrays: (bricks, z, y, x, channel) with a mask of known voxels -----------------


def _spans(index: np.ndarray, size: int, dim: int) -> np.ndarray:
    """For each brick coordinate, the number of 0..size-1 cells inside the volume along an axis, as a 0/1 row per brick."""
    at = index[:, None] * size + np.arange(size)[None, :]
    return at < dim


def measures(values: np.ndarray, mask: np.ndarray, place: np.ndarray, vm: VolumeMeta, level: int) -> dict[str, np.ndarray]:
    """Valid voxels and, per channel, known voxels, minimum, maximum and sum, unknown voxels of the volume as background."""
    dims, (mx, my, mz) = vm.at_level(level), vm.brick
    n = np.ones(len(place), dtype=np.int64)
    for k, m in enumerate((mx, my, mz)):
        n *= _spans(place[:, k], m, dims[k]).sum(axis=1)
    axes = (1, 2, 3)
    known = mask.sum(axis=axes, dtype=np.int64)
    low = np.where(mask, values, np.iinfo(np.int64).max).min(axis=axes)
    high = np.where(mask, values, np.iinfo(np.int64).min).max(axis=axes)
    total = np.where(mask, values, 0).sum(axis=axes, dtype=np.int64) + vm.background * (n[:, None] - known)
    partly = known < n[:, None]
    low = np.where(partly, np.minimum(low, vm.background), low)
    high = np.where(partly, np.maximum(high, vm.background), high)
    return {"n": n, "known": known, "bmin": low, "bmax": high, "bsum": total}


def half_bodies(values: np.ndarray, mask: np.ndarray, place: np.ndarray, vm: VolumeMeta, level: int):
    """Bodies of the parents of some bricks of a level: mean over the children cells in the volume, absent ones as background.

    Cells are paired by their place in the volume, not in the child, so odd bricks work as well.
    Returns values, mask, places and the children's parent numbers.
    """
    parents, owner = np.unique(place >> 1, axis=0, return_inverse=True)
    owner = owner.reshape(-1)
    mx, my, mz = vm.brick
    c = vm.channels
    sums = np.zeros((len(parents), 2, mz, 2, my, 2, mx, c), dtype=np.int64)
    counts = np.zeros(sums.shape, dtype=np.int8)
    ox, oy, oz = (place[:, k] & 1 for k in range(3))
    sums[owner, oz, :, oy, :, ox] = np.where(mask, values, 0)
    counts[owner, oz, :, oy, :, ox] = mask
    pairs = (len(parents), mz, 2, my, 2, mx, 2, c)
    total = sums.reshape(pairs).sum(axis=(2, 4, 6))
    cnt = counts.reshape(pairs).sum(axis=(2, 4, 6), dtype=np.int64)
    inside = np.ones((len(parents), mz, my, mx), dtype=np.int64)
    for k, (m, d) in enumerate(zip((mx, my, mz), vm.at_level(level), strict=True)):
        at = 2 * (parents[:, k][:, None] * m + np.arange(m)[None, :])
        each = np.clip(d - at, 0, 2)
        shape = [len(parents), 1, 1, 1]
        shape[3 - k] = m
        inside = inside * each.reshape(shape)
    inside = inside[..., None]
    total = total + vm.background * (inside - cnt)
    whole = np.maximum(inside, 1)
    mean = np.where(total < 0, -(-total // whole), total // whole)
    return mean, cnt > 0, parents, owner


def subtree_measures(own: dict[str, np.ndarray], kids: tuple[np.ndarray, np.ndarray], owner: np.ndarray, places: np.ndarray, vm: VolumeMeta, level: int) -> None:
    """Adds smin and smax of the bricks at ``places`` of a level: their own and their children's, absent children as background."""
    low, high = own["bmin"].copy(), own["bmax"].copy()
    np.minimum.at(low, owner, kids[0])
    np.maximum.at(high, owner, kids[1])
    want = np.ones(len(places), dtype=np.int64)
    for k, d in enumerate(vm.bricks_at(level - 1)):
        want *= np.clip(d - 2 * places[:, k], 0, 2)
    missing = np.bincount(owner, minlength=len(places)) < want
    low[missing] = np.minimum(low[missing], vm.background)
    high[missing] = np.maximum(high[missing], vm.background)
    own["smin"], own["smax"] = low, high


def _keys(place: np.ndarray, bits: int) -> np.ndarray:
    out = np.zeros(len(place), dtype=np.int64)
    for i in range(bits):
        for k in range(3):
            out |= (place[:, k].astype(np.int64) >> i & 1) << (3 * i + k)
    return out


def _bodies(column: pa.Array, shape: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
    flat = column.flatten()
    mask = flat.is_valid().to_numpy(zero_copy_only=False).reshape(-1, *shape)
    return flat.fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64).reshape(-1, *shape), mask


def _lists(rows: np.ndarray, mask: np.ndarray | None, kind: pa.DataType) -> pa.Array:
    flat = rows.reshape(len(rows), -1)
    offsets = np.arange(len(rows) + 1, dtype=np.int32) * flat.shape[1]
    body = pa.array(flat.ravel(), kind, mask=None if mask is None else ~mask.ravel())
    return pa.ListArray.from_arrays(pa.array(offsets), body)


def _rows(level: int, values, mask, place, stats, vm: VolumeMeta) -> pa.Table:
    columns = {"level": pa.array(np.full(len(place), level, dtype=np.int32)), "key": pa.array(_keys(place, vm.key_bits))}
    columns |= {f"i{a}": pa.array(place[:, k].astype(np.int32)) for k, a in enumerate(AXES)}
    columns |= {"n": pa.array(stats["n"]), "body": _lists(values.astype(np.int64), mask, pa.int32())}
    return pa.table(columns | {s: _lists(stats[s], None, pa.int64()) for s in STATS})


def _climb(vm: VolumeMeta, base: int, top: int):
    """One group: leaves from their patches (``base`` 0), then each level up to ``top`` from the level below.

    Rows with ``off`` are patches; others are bricks of the pool, either old leaves under a patch or
    siblings that stay.  Returns the bricks that are new.
    """
    mx, my, mz = vm.brick
    shape = (mz, my, mx, vm.channels)

    def stacked(table: pa.Table) -> tuple:
        place = np.stack([table[f"i{a}"].to_numpy() for a in AXES], axis=1).astype(np.int64) if table.num_rows else np.zeros((0, 3), np.int64)
        values, mask = _bodies(table["body"].combine_chunks(), shape) if table.num_rows else (np.zeros((0, *shape), np.int64), np.zeros((0, *shape), bool))
        low, high = (table[s].combine_chunks().flatten().to_numpy().reshape(-1, vm.channels) if table.num_rows else np.zeros((0, vm.channels), np.int64) for s in ("smin", "smax"))
        return place, values, mask, low, high

    def run(table: pa.Table) -> pa.Table:
        levels = table["level"].to_numpy()
        patch = table["off"].is_valid().to_numpy()
        fresh = table["fresh"].to_numpy(zero_copy_only=False)
        out = []
        here = None  # places, values, mask, smin, smax of the new bricks of the level
        if base == 0:
            blocks = table.filter(pa.array(patch))
            place = np.stack([blocks[f"i{a}"].to_numpy() for a in AXES], axis=1).astype(np.int64)
            values, mask = np.zeros((len(place), *shape), np.int64), np.zeros((len(place), *shape), bool)
            old = stacked(table.filter(pa.array(~patch & (levels == 0))))
            number = {tuple(p): i for i, p in enumerate(place.tolist())}
            at = np.array([number.get(tuple(p), -1) for p in old[0].tolist()], dtype=np.int64)
            values[at[at >= 0]], mask[at[at >= 0]] = old[1][at >= 0], old[2][at >= 0]
            offsets = blocks["off"].combine_chunks()
            owner = np.repeat(np.arange(len(place)), np.diff(offsets.offsets.to_numpy()))
            off = offsets.flatten().to_numpy()
            values.reshape(len(place), -1)[owner, off] = blocks["val"].combine_chunks().flatten().to_numpy()
            mask.reshape(len(place), -1)[owner, off] = True
            stats = measures(values, mask, place, vm, 0)
            stats["smin"], stats["smax"] = stats["bmin"], stats["bmax"]
            out.append(_rows(0, values, mask, place, stats, vm))
            here = (place, values, mask, stats["smin"], stats["smax"])
            stay = tuple(x[at < 0] for x in old)
        else:
            here = stacked(table.filter(pa.array(fresh & (levels == base))))
            stay = stacked(table.filter(pa.array(~fresh & (levels == base))))
        for level in range(base + 1, top + 1):
            place, values, mask, low, high = (np.concatenate(x) for x in zip(here, stay, strict=True))
            values, mask, parents, owner = half_bodies(values, mask, place, vm, level - 1)
            stats = measures(values, mask, parents, vm, level)
            subtree_measures(stats, (low, high), owner, parents, vm, level)
            out.append(_rows(level, values, mask, parents, stats, vm))
            here = (parents, values, mask, stats["smin"], stats["smax"])
            stay = stacked(table.filter(pa.array(~patch & ~fresh & (levels == level))))
        return pa.concat_tables(out)

    return run


# --- the pool -----------------------------------------------------------------------------------


@dataclass
class BrickPool:
    """A pool under ``path``; ``commits`` numbers its versions, each a folder that a replay overwrites."""

    spark: SparkSession
    vm: VolumeMeta
    path: str
    commits: list[int] = field(default_factory=list)

    @classmethod
    def create(cls, spark: SparkSession, vm: VolumeMeta, path: str | None = None) -> BrickPool:
        """A pool that holds nothing: the root is background and can be read at once."""
        return cls(spark, vm, path or storage.new_path(spark, f"pool-{vm.name}"))

    def _folder(self, version: int) -> str:
        return f"{self.path}/version={version}"

    def insert(self, block: DataFrame, version: int | None = None, height: int | None = None, alone: int | None = None) -> int:
        """Commit one version with the voxels (x, y, z, c, v) of a block, which overwrite older ones; return its number.

        ``height`` (levels per group) and ``alone`` set how the work is shared out: with ``alone``, one task builds everything
        below a brick of that level, group by group, and one task what lies above.  An empty block commits a version without
        bricks.  A version that is committed again is replaced and must be the last one.
        """
        vm = self.vm
        version = (self.commits[-1] + 1 if self.commits else 0) if version is None else version
        if self.commits and version < self.commits[-1]:
            raise ValueError("only the last version can be committed again")
        before = [v for v in self.commits if v != version]
        storage.drop(self.spark, self._folder(version))
        patches = storage.keep(leaf_patches(block, vm), "patches")
        height = group_height(vm) if height is None else max(1, height)
        base = 0
        while base == 0 or base < vm.top:
            top = min(base + height, vm.top if alone is None or base >= alone else alone)
            fresh = patches if base == 0 else self._rows([version]).filter(F.col("level") == base)
            grouped = self._inputs(fresh, before, patches, base, top)
            if alone is None:
                out = grouped.groupBy("shard")
            else:  # dealt out by builder, which the groups of a builder need no further exchange for
                builder = F.expr(f"shiftright(key, 3 * ({alone} - level))") if base < alone else F.lit(0).cast("long")
                out = grouped.withColumn("builder", builder).repartition(8 ** (vm.top - alone) if base < alone else 1, "builder").groupBy("builder", "shard")
            out = out.applyInArrow(_climb(vm, base, top), SCHEMA)
            out.sortWithinPartitions("level", "key").write.mode("append").partitionBy("level").parquet(self._folder(version))
            base = top
            if vm.top == 0:
                break
        return self._mark(version)

    def _inputs(self, fresh: DataFrame, before: list[int], patches: DataFrame, base: int, top: int) -> DataFrame:
        """What the groups of one step need: patches or new bricks of level ``base``, old leaves, siblings that stay."""
        vm = self.vm
        shard = F.expr(f"shiftright(key, 3 * ({top} - level))").alias("shard")
        cols = ["level", "key", "ix", "iy", "iz", "body", "smin", "smax"]
        empty = [F.lit(None).cast("array<int>").alias(k) for k in ("off", "val")]
        if base == 0:
            rows = fresh.select(F.lit(0).alias("level"), "key", "ix", "iy", "iz", *(F.lit(None).cast(t).alias(k) for k, t in (("body", "array<int>"), ("smin", "array<long>"), ("smax", "array<long>"))), "off", "val", F.lit(True).alias("fresh"))
        else:
            rows = fresh.select(*cols, *empty, F.lit(True).alias("fresh"))
        if before:
            touched = touched_keys(patches, base, top)
            old = self._rows(before).filter(F.col("level").between(base, top - 1 if top > base else base))
            if top == base:
                stay = old.join(touched, ["level", "key"], "left_semi")
            else:
                parents = touched.filter(F.col("level") > base).select((F.col("level") - 1).alias("level"), F.col("key").alias("parent"))
                stay = old.withColumn("parent", F.shiftright("key", 3)).join(parents, ["level", "parent"], "left_semi")
                # touched bricks above the leaves are made anew
                stay = stay.join(touched.filter("level > 0"), ["level", "key"], "left_anti")
            rows = rows.unionByName(stay.select(*cols, *empty, F.lit(False).alias("fresh")))
        return rows.withColumn("shard", shard)

    def _rows(self, versions: list[int]) -> DataFrame:
        """Newest brick of each (level, key) among some versions: one scan of the bodies and one of the keys, which decide."""
        names = [f.split()[0] for f in SCHEMA.split(", ")]
        if not versions:
            return self.spark.createDataFrame([], SCHEMA)
        rows = self.spark.read.schema(f"version int, {SCHEMA}").option("basePath", self.path).parquet(*map(self._folder, versions))
        if len(versions) > 1:
            newest = rows.groupBy("level", "key").agg(F.max("version").alias("version"))
            rows = rows.join(newest, ["level", "key", "version"], "left_semi")
        return rows.select(*names)

    def bricks(self, version: int | None = None) -> DataFrame:
        """Bricks as of a version (default: the last): level, key, ix, iy, iz, n, body and statistics per channel."""
        return self._rows([v for v in self.commits if version is None or v <= version])

    def stats(self, version: int | None = None) -> DataFrame:
        """Statistics per brick and inserted channel: level, ix, iy, iz, c, n, bmin, bmax, bsum, avg, smin, smax."""
        return channel_stats(self.bricks(version))

    def voxels(self, version: int | None = None, level: int | None = None) -> DataFrame:
        """Inserted voxels (level, x, y, z, c, v) of all levels or one."""
        rows = self.bricks(version)
        return unpacked(rows if level is None else rows.filter(F.col("level") == level), self.vm)

    def compacted(self) -> BrickPool:
        """The newest bricks as a pool of one version, after which old ones can be dropped."""
        out = BrickPool.create(self.spark, self.vm)
        out.commit(self.bricks())
        return out

    def compact(self) -> None:
        """Put all versions but the last into one, in place, so that readers scan two folders; older states cannot be read any more.

        The last version stays apart, as a stream may commit it again.
        """
        early = self.commits[:-1]
        if len(early) < 2:
            return
        merged = f"{self.path}/_merged-{early[-1]}"
        self._rows(early).sortWithinPartitions("level", "key").write.mode("overwrite").partitionBy("level").parquet(merged)
        storage.touch(self.spark, f"{merged}/{DONE}")
        self._replace(early, merged)
        self.commits = self.commits[-2:]

    def _replace(self, versions: list[int], merged: str) -> None:
        for v in versions:
            storage.drop(self.spark, self._folder(v))
        storage.rename(self.spark, merged, self._folder(versions[-1]))

    def commit(self, bricks: DataFrame) -> int:
        """Write finished bricks as the next version."""
        version = self.commits[-1] + 1 if self.commits else 0
        storage.drop(self.spark, self._folder(version))
        bricks.sortWithinPartitions("level", "key").write.partitionBy("level").parquet(self._folder(version))
        return self._mark(version)

    def _mark(self, version: int) -> int:
        storage.touch(self.spark, f"{self._folder(version)}/{DONE}")
        self.commits = [*(v for v in self.commits if v != version), version]
        return version

    def region(self, box: dict[str, tuple[int, int]], level: int, version: int | None = None) -> DataFrame:
        """Voxels of a closed box at a level: whole bricks are skipped by their coordinates before bodies are opened."""
        rows = self.bricks(version).filter(F.col("level") == level)
        for a, m in zip(AXES, self.vm.brick, strict=True):
            if a in box:
                rows = rows.filter(F.col(f"i{a}").between(box[a][0] // m, box[a][1] // m))
        cells = unpacked(rows, self.vm)
        for a, (low, high) in box.items():
            cells = cells.filter(F.col(a).between(low, high))
        return cells


def leaf_patches(block: DataFrame, vm: VolumeMeta) -> DataFrame:
    """One row per leaf brick of a block: its key, coordinates and the offsets and values to write.

    Of equal places in one block the greatest value is written; voxels outside the volume and null ones are none of it.
    """
    mx, my, mz = vm.brick
    inside = " and ".join(f"{a} >= 0 and {a} < {d}" for a, d in zip(AXES, vm.dims, strict=True))
    off = F.expr(f"cast((((z % {mz}) * {my} + y % {my}) * {mx} + x % {mx}) * {vm.channels} + c as int)")
    rows = block.filter(inside).filter(f"v is not null and c >= 0 and c < {vm.channels}")
    rows = rows.select(*(c.cast("int").alias(k) for k, c in coords(0, vm).items()), off.alias("off"), F.col("v").cast("int").alias("v"))
    # dealt out once by brick; both aggregations use that
    one = rows.repartition("ix", "iy", "iz").groupBy("ix", "iy", "iz", "off").agg(F.max("v").alias("v"))
    packed = one.groupBy("ix", "iy", "iz").agg(F.sort_array(F.collect_list(F.struct("off", "v"))).alias("cells"))
    return packed.select(morton3(F.col("ix"), F.col("iy"), F.col("iz"), vm.key_bits).alias("key"), "ix", "iy", "iz", F.col("cells.off").alias("off"), F.col("cells.v").alias("val"))


def touched_keys(patches: DataFrame, base: int, top: int) -> DataFrame:
    """(level, key) of the insertion paths from level ``base`` to ``top``, in closed form from the leaf keys."""
    rows = patches.select(F.expr(f"shiftright(key, {3 * base})").alias("key")).distinct()
    rows = rows.select(F.explode(F.sequence(F.lit(base), F.lit(top))).alias("level"), F.col("key").alias("leaf"))
    return rows.select("level", F.expr(f"shiftright(leaf, 3 * (level - {base}))").alias("key")).distinct()


def channel_stats(bricks: DataFrame) -> DataFrame:
    """Rows per brick and inserted channel, straight from the bricks' arrays."""
    zipped = F.explode(F.expr("filter(transform(sequence(0, size(known) - 1), c -> struct(c, known[c] as known, bmin[c] as bmin, bmax[c] as bmax, bsum[c] as bsum, smin[c] as smin, smax[c] as smax)), s -> s.known > 0)"))
    rows = bricks.select("level", "ix", "iy", "iz", "n", zipped.alias("s"))
    return rows.select("level", "ix", "iy", "iz", "s.c", "n", "s.bmin", "s.bmax", "s.bsum", F.expr("s.bsum div n").alias("avg"), "s.smin", "s.smax")


def unpacked(bricks: DataFrame, vm: VolumeMeta) -> DataFrame:
    """Inserted voxels (level, x, y, z, c, v) of bricks."""
    mx, my, mz = vm.brick
    c = vm.channels
    rows = bricks.select("level", "ix", "iy", "iz", F.posexplode("body").alias("off", "v")).filter("v is not null")
    return rows.select("level", F.expr(f"ix * {mx} + off div {c} % {mx}").cast("int").alias("x"), F.expr(f"iy * {my} + off div {c * mx} % {my}").cast("int").alias("y"), F.expr(f"iz * {mz} + off div {c * mx * my}").cast("int").alias("z"), F.expr(f"off % {c}").alias("c"), F.col("v").cast("long").alias("v"))


def parents_of(bricks: DataFrame, vm: VolumeMeta, level: int) -> DataFrame:
    """Parents (level + 1) of the bricks of one level, from their bodies alone: key, ix, iy, iz, body."""
    shape = (vm.brick[2], vm.brick[1], vm.brick[0], vm.channels)

    def run(table: pa.Table) -> pa.Table:
        place = np.stack([table[f"i{a}"].to_numpy() for a in AXES], axis=1).astype(np.int64)
        values, mask, parents, _ = half_bodies(*_bodies(table["body"].combine_chunks(), shape), place, vm, level)
        return pa.table({"key": pa.array(_keys(parents, vm.key_bits)), **{f"i{a}": pa.array(parents[:, k].astype(np.int32)) for k, a in enumerate(AXES)}, "body": _lists(values, mask, pa.int32())})

    rows = bricks.filter(F.col("level") == level).select(F.shiftright("key", 3).alias("parent"), "ix", "iy", "iz", "body")
    return rows.groupBy("parent").applyInArrow(run, "key long, ix int, iy int, iz int, body array<int>")


def open_pool(spark: SparkSession, vm: VolumeMeta, path: str) -> BrickPool:
    """A pool that was written before: its versions are the folders with the marker; a compaction that was cut off is finished."""
    where, system = storage.hadoop_path(spark, path)
    found = [f.getPath().getName() for f in system.listStatus(where)] if system.exists(where) else []
    done = [n for n in found if storage.exists(spark, f"{path}/{n}/{DONE}")]
    versions = sorted(int(n.split("=")[1]) for n in done if n.startswith("version="))
    pool = BrickPool(spark, vm, path, versions)
    for n in done:
        if n.startswith("_merged-"):
            last = int(n.split("-")[1])
            pool._replace([v for v in versions if v < last] + [last], f"{path}/{n}")
            pool.commits = [last] + [v for v in versions if v > last]
    return pool
