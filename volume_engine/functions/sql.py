"""The SQL surface: functions of keys and levels as SQL text, and table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .grid import KEY_BITS, VolumeMeta, bfs_base


def _spread(name: str, axis: int, bits: int) -> str:
    return " | ".join(f"shiftleft(shiftright({name}, {i}) & 1L, {3 * i + axis})" for i in range(bits))


def register(spark: SparkSession, vm: VolumeMeta, bits: int = KEY_BITS) -> None:
    """Temporary SQL functions: morton3, parent_key, child_key, octant_of, bfs_index, node_box and optimal_level of a volume.

    They are expressions that are put into the query's plan, so they cost no call.
    """
    mx, my, mz = vm.brick
    base = "element_at(array(" + ", ".join(f"{bfs_base(vm.top - l)}L" for l in range(vm.top + 1)) + "), level + 1)"
    unspread = lambda axis: " | ".join(f"shiftleft(shiftright(key, {3 * i + axis}) & 1L, {i})" for i in range(bits))
    edges = ", ".join(f"'{a}0', shiftleft(({unspread(k)}) * {m}L, level), '{a}1', least(shiftleft(({unspread(k)}) * {m}L + {m}L, level), {d}L)" for k, (a, m, d) in enumerate(zip("xyz", (mx, my, mz), vm.dims, strict=True)))
    texts = {
        "morton3(ix BIGINT, iy BIGINT, iz BIGINT) RETURNS BIGINT": " | ".join(_spread(n, k, bits) for k, n in enumerate(("ix", "iy", "iz"))),
        "parent_key(key BIGINT) RETURNS BIGINT": "shiftright(key, 3)",
        "child_key(key BIGINT, octant INT) RETURNS BIGINT": "shiftleft(key, 3) | octant",
        "octant_of(key BIGINT) RETURNS INT": "cast(key & 7 as int)",
        "bfs_index(level INT, key BIGINT) RETURNS BIGINT": f"{base} + key",
        "node_box(level INT, key BIGINT) RETURNS STRUCT<x0: BIGINT, x1: BIGINT, y0: BIGINT, y1: BIGINT, z0: BIGINT, z1: BIGINT>": f"named_struct({edges})",
        "optimal_level(depth DOUBLE, pixel_angle DOUBLE) RETURNS INT": f"cast(greatest(0, least({vm.top}, floor(log2(greatest(depth * pixel_angle, 1D))))) as int)",
    }
    for head, body in texts.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")


@udtf(returnType="octant: int, child: bigint")
class OctantChildren:
    """The eight children of a node's key."""

    def eval(self, key: int):
        for octant in range(8):
            yield octant, key * 8 + octant


@udtf(returnType="level: int, key: bigint")
class AncestorPath:
    """A key and its ancestors up to the level ``top``."""

    def eval(self, key: int, top: int):
        for level in range(top + 1):
            yield level, key >> (3 * level)


def register_tables(spark: SparkSession) -> None:
    spark.udtf.register("octant_children", OctantChildren)
    spark.udtf.register("ancestor_path", AncestorPath)
