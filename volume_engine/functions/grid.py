"""Geometry and addressing of the bricked pyramid: levels, brick coordinates, Morton keys, boxes, breadth-first numbers."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column
from pyspark.sql import functions as F

AXES = ("x", "y", "z")
#: Bits of a coordinate in a Morton key: three axes fill a long.
KEY_BITS = 21


@dataclass(frozen=True)
class VolumeMeta:
    """What must be declared of a volume before its first block: grid, channels, brick and intensity range."""

    name: str
    dims: tuple[int, int, int]
    brick: tuple[int, int, int]
    channels: int = 1
    background: int = 0
    lo: int = 0
    hi: int = 65535
    voxel_bytes: int = 2

    def __post_init__(self):
        if min(self.dims) < 1 or min(self.brick) < 1 or self.channels < 1:
            raise ValueError("dimensions, brick and channels must be positive")

    @property
    def top(self) -> int:
        """Level of the root brick."""
        return fit_levels(self.dims, self.brick)

    @property
    def key_bits(self) -> int:
        """Bits an axis that the Morton keys of the volume's bricks need."""
        return max(1, self.top)

    def at_level(self, level: int) -> tuple[int, int, int]:
        """Voxel dimensions of a level."""
        return tuple(-(-d // (1 << level)) for d in self.dims)

    def bricks_at(self, level: int) -> tuple[int, int, int]:
        return tuple(-(-d // m) for d, m in zip(self.at_level(level), self.brick, strict=True))

    def threshold(self, value: float, kind: str = "absolute") -> float:
        """Homogeneity threshold in intensities; ``percent`` is of the declared range."""
        return value if kind == "absolute" else value * (self.hi - self.lo) / 100.0

    def with_brick(self, *brick: int) -> VolumeMeta:
        return replace(self, brick=brick)


def fit_levels(dims, brick) -> int:
    """Smallest N for which a root brick of N halvings covers the volume along every axis."""
    n = 0
    while any(m << n < d for d, m in zip(dims, brick, strict=True)):
        n += 1
    return n


def levels_sql(brick, dims=("dx", "dy", "dz")) -> str:
    """``fit_levels`` as SQL text; sizes of the brick and dimensions are numbers or columns."""
    short = " or ".join(f"shiftleft(cast({m} as bigint), n) < {d}" for m, d in zip(brick, dims, strict=True))
    return f"size(filter(sequence(0, {KEY_BITS}), n -> {short}))"


def fit_brick(dims, candidates) -> tuple[int, int, int]:
    """Brick with one size per axis that wastes the least virtual volume (fewest levels on ties)."""
    options = [(bx, by, bz) for bx in candidates for by in candidates for bz in candidates]

    def waste(b):
        n = fit_levels(dims, b)
        return (b[0] << n) * (b[1] << n) * (b[2] << n), n, b

    return min(options, key=waste)


def check_brick(size: int) -> int:
    """Brick sizes are even, so that every parent cell has its children in one child brick."""
    if size < 2 or size % 2:
        raise ValueError("brick sizes must be even")
    return size


def spread_bits(col: Column, axis: int, bits: int) -> Column:
    out = F.lit(0).cast("long")
    for i in range(bits):
        out = out.bitwiseOR(F.shiftleft(F.shiftright(col.cast("long"), i).bitwiseAND(F.lit(1).cast("long")), 3 * i + axis))
    return out


def morton3(ix: Column, iy: Column, iz: Column, bits: int = KEY_BITS) -> Column:
    """Interleaved key of brick coordinates: parent = key >> 3, octant = key & 7.

    A coordinate that does not fit in ``bits`` (negative ones never do) is an error, as its key would be another brick's.
    """
    if not 0 < bits <= KEY_BITS:
        raise ValueError(f"a key holds 1 to {KEY_BITS} bits an axis")
    key = spread_bits(ix, 0, bits).bitwiseOR(spread_bits(iy, 1, bits)).bitwiseOR(spread_bits(iz, 2, bits))
    every = ix.cast("long").bitwiseOR(iy.cast("long")).bitwiseOR(iz.cast("long"))
    return F.when(F.shiftright(every, bits) != 0, F.raise_error(F.lit(f"brick coordinate beyond {bits} bits")).cast("long")).otherwise(key)


def demorton3(key: Column, axis: int, bits: int = KEY_BITS) -> Column:
    out = F.lit(0).cast("long")
    for i in range(bits):
        out = out.bitwiseOR(F.shiftleft(F.shiftright(key, 3 * i + axis).bitwiseAND(F.lit(1).cast("long")), i))
    return out


def bfs_base(depth: int) -> int:
    """Breadth-first number of the first node of a depth."""
    return (8**depth - 1) // 7


def bfs_index(level: Column, key: Column, top: int) -> Column:
    base = F.lit(None).cast("long")
    for l in range(top + 1):
        base = F.when(level == l, F.lit(bfs_base(top - l))).otherwise(base)
    return base + key


def inside(cell: Column, dim: int, size: int = 2) -> Column:
    """Number of the ``size`` children of a cell along an axis that lie in the volume."""
    return F.least(F.lit(dim), (cell + 1) * size) - cell * size


def coords(level: int, vm: VolumeMeta) -> dict[str, Column]:
    """Brick coordinates ix, iy, iz of voxels x, y, z of a level."""
    return {f"i{a}": F.expr(f"{a} div {m}") for a, m in zip(AXES, vm.brick, strict=True)}


def bits_needed(n: int) -> int:
    return max(1, (max(n, 1) - 1).bit_length())


def addressing_limits(levels: int, brick: int = 64, pointer_bits: int = 22) -> dict[str, int]:
    """What a node entry can address at a number of levels."""
    nodes = bfs_base(levels)
    return {"levels": levels, "nodes": nodes, "addressable": 8 << pointer_bits, "fits": int(nodes <= 8 << pointer_bits), "edge": brick << (levels - 1), "address_bits": bits_needed(nodes), "buffer_bytes": 8 * nodes}
