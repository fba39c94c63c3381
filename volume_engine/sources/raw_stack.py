"""Raw image stacks as a Spark source, and image and pool sinks.

A stack is a folder of files ``<channel>_<slice>.raw``, each one slice of little-endian unsigned
samples row by row.  ``spark.read.format("raw_stack")`` makes one partition per file and gives voxels
(x, y, z, c, v); samples equal to ``background`` are left out.  Files are opened by the tasks, so the
folder has to be one that all executors see.
"""

from __future__ import annotations

import os
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

NAME = re.compile(r"^(\d+)_(\d+)\.raw$")


class SliceFile(InputPartition):
    def __init__(self, path: str, channel: int, z: int):
        self.path, self.channel, self.z = path, channel, z


class RawStackReader(DataSourceReader):
    def __init__(self, options: dict):
        self.folder = options["path"].removeprefix("file://")
        self.width, self.bytes = int(options["width"]), int(options.get("voxelbytes", 2))
        self.background = int(options.get("background", 0))
        self.wanted = {k: int(options[k]) for k in ("c", "z") if k in options}

    def partitions(self):
        found = []
        for name in sorted(os.listdir(self.folder)):
            if m := NAME.match(name):
                c, z = int(m[1]), int(m[2])
                if self.wanted.get("c", c) == c and self.wanted.get("z", z) == z:
                    found.append(SliceFile(f"{self.folder}/{name}", c, z))
        return found or [None]

    def read(self, part):
        if part is None:
            return
        cells = np.fromfile(part.path, dtype=f"<u{self.bytes}")
        at = np.flatnonzero(cells != self.background)
        n = len(at)
        yield pa.record_batch({
            "x": pa.array((at % self.width).astype(np.int32)), "y": pa.array((at // self.width).astype(np.int32)),
            "z": pa.array(np.full(n, part.z, np.int32)), "c": pa.array(np.full(n, part.channel, np.int32)), "v": pa.array(cells[at].astype(np.int64)),
        })


class RawStack(DataSource):
    @classmethod
    def name(cls) -> str:
        return "raw_stack"

    def schema(self) -> str:
        return "x int, y int, z int, c int, v long"

    def reader(self, schema):
        return RawStackReader(dict(self.options))


def read_stack(spark: SparkSession, folder: str, width: int, voxel_bytes: int = 2, background: int = 0, **files: int) -> DataFrame:
    """A stack, or its files of one channel (``c``) or slice (``z``): the others are not opened."""
    spark.dataSource.register(RawStack)
    return spark.read.format("raw_stack").option("width", width).option("voxelbytes", voxel_bytes).option("background", background).options(**files).load(folder)


def write_slice(folder: str, channel: int, z: int, cells: np.ndarray) -> None:
    """One slice of a stack (rows of samples); used by scanners and tests."""
    cells.astype("<u2").tofile(f"{folder}/{channel}_{z}.raw")


def write_image(image: DataFrame, path: str, width: int, height: int, scale: float = 255.0) -> None:
    """A finished colour image (px, py, r, g, b) as a binary PPM file; its pixels come to the driver."""
    out = np.zeros((height, width, 3), dtype=np.uint8)
    for r in image.select("px", "py", "r", "g", "b").collect():  # as many rows as the screen has pixels
        out[r.py, r.px] = [min(255, max(0, round(v * scale))) for v in (r.r, r.g, r.b)]
    with open(path, "wb") as f:
        f.write(f"P6 {width} {height} 255\n".encode())
        f.write(out.tobytes())
