"""Chromatic correction: a matrix per channel applied while sampling, and the resampled channel as baseline."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.grid import AXES, VolumeMeta

Matrix = list[list[float]]


def identity() -> Matrix:
    return [[1.0, 0.0, 0.0, 0.0], [0.0, 1.0, 0.0, 0.0], [0.0, 0.0, 1.0, 0.0]]


def translation(x: float, y: float, z: float) -> Matrix:
    return [[*row[:3], t] for row, t in zip(identity(), (x, y, z), strict=True)]


def scaling(x: float, y: float | None = None, z: float | None = None) -> Matrix:
    return [[s if k == j else 0.0 for j in range(3)] + [0.0] for k, s in enumerate((x, x if y is None else y, x if z is None else z))]


def rotation(degrees: float, axis: str = "z") -> Matrix:
    """About an axis through the origin; whole quarters of a turn are exact."""
    k = AXES.index(axis)
    c, s = (round(f(math.radians(degrees)), 15) + 0.0 for f in (math.cos, math.sin))
    i, j = (k + 1) % 3, (k + 2) % 3
    out = identity()
    out[i][i], out[i][j], out[j][i], out[j][j] = c, -s, s, c
    return out


def compose(*matrices: Matrix) -> Matrix:
    """One matrix that applies the given ones, the last first."""
    whole = np.eye(4)
    for m in matrices:
        whole = whole @ np.vstack([np.array(m, dtype=float), [0, 0, 0, 1]])
    return whole[:3].tolist()


def inverse(matrix: Matrix) -> Matrix:
    return np.linalg.inv(np.vstack([np.array(matrix, dtype=float), [0, 0, 0, 1]]))[:3].tolist()


def resample_channel(voxels: DataFrame, channel: int, matrix: Matrix, vm: VolumeMeta) -> DataFrame:
    """The volume with one channel copied through its matrix: each voxel takes the one its centre is mapped to, or background.

    Needs the whole channel and has to be done again for another matrix.  Every voxel of the channel is
    sent to the few places whose centres can map into it; the exact condition picks among them.
    """
    back = np.array(inverse(matrix))
    reach = [int(math.ceil(np.abs(back[k, :3]).sum() / 2)) + 1 for k in range(3)]
    rest, own = voxels.filter(F.col("c") != channel), voxels.filter(F.col("c") == channel)

    def at(m, row, names) -> str:
        return " + ".join(f"{float(m[row][j])!r}D * ({n} + 0.5D)" for j, n in enumerate(names)) + f" + {float(m[row][3])!r}D"

    places = own.select(*(F.col(a).alias(f"s{a}") for a in AXES), "c", "v", *(F.expr(f"cast(floor({at(back, k, ['x', 'y', 'z'])}) as int)").alias(f"m{a}") for k, a in enumerate(AXES)))
    for a, r, d in zip(AXES, reach, vm.dims, strict=True):
        # the sequence is empty (null) for places beyond the volume
        places = places.withColumn(a, F.explode(F.expr(f"if(m{a} + {r} < 0 or m{a} - {r} > {d - 1}, cast(null as array<int>), sequence(greatest(0, m{a} - {r}), least({d - 1}, m{a} + {r})))")))
    for k, a in enumerate(AXES):
        places = places.filter(F.expr(f"floor({at(matrix, k, AXES)}) = s{a}"))
    return rest.select(*AXES, "c", "v").unionByName(places.select(*AXES, "c", "v"))


def overlap(voxels: DataFrame, fixed: int, moving: int, shifts: list[tuple[int, int, int]]) -> DataFrame:
    """For each trial shift of a channel (dx, dy, dz): voxels that meet another channel's and the sum of the smaller intensities.

    A table of shifts is swapped without touching the volume; the best shift has the greatest overlap.
    """
    table = F.broadcast(voxels.sparkSession.createDataFrame(shifts, "dx int, dy int, dz int"))
    moved = voxels.filter(F.col("c") == moving).join(table).select(*((F.col(a) + F.col(f"d{a}")).alias(a) for a in AXES), "dx", "dy", "dz", F.col("v").alias("w"))
    met = voxels.filter(F.col("c") == fixed).select(*AXES, "v").join(moved, list(AXES))
    return met.groupBy("dx", "dy", "dz").agg(F.count("*").alias("voxels"), F.sum(F.least("v", "w")).alias("overlap"))
