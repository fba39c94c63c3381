"""Volumes opened once: their declaration and brick pool are kept beside each other while their tables stay as they are."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from .. import storage
from ..functions.grid import VolumeMeta
from ..operators.octree import nodes_of_bricks
from ..operators.pool import BrickPool
from .volumes import open_volume

#: Tables that each volume is read from.
TABLES = {
    "ribbon": ("documents",), "scan": ("events",), "sales": ("lineitem", "part"), "vec": ("embeddings",),
    "conversations": ("conversations",), "labels": ("labels",), "benchmark": ("benchmark",),
}


@dataclass
class Opened:
    """A volume's sparse voxels, its declaration and, from its first use on, its pool."""

    voxels: DataFrame
    vm: VolumeMeta
    state: tuple
    _pool: BrickPool | None = None

    @property
    def pool(self) -> BrickPool:
        if self._pool is None or not storage.exists(self._pool.spark, self._pool.path):
            built = BrickPool.create(self.voxels.sparkSession, self.vm)
            built.insert(self.voxels)
            self._pool = built
        return self._pool

    def nodes(self, threshold: float) -> DataFrame:
        """Octree nodes with their averages and homogeneity, read off the pool without its bodies."""
        return nodes_of_bricks(self.pool.bricks(), self.vm, threshold)


_opened: dict[tuple, Opened] = {}


def volume(spark: SparkSession, sf_dir: str, name: str, fresh: bool = False) -> Opened:
    """The volume ``name`` of a directory of tables; read anew if a table has changed since, or if ``fresh``."""
    state = tuple(storage.state_of(spark, f"{sf_dir}/{t}.parquet") for t in TABLES[name])
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if fresh or key not in _opened or _opened[key].state != state:
        _opened[key] = Opened(*open_volume(spark, sf_dir, name), state)
    return _opened[key]
