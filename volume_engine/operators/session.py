"""The mode controller of a viewer: approximate frames while something moves, refinement when it rests."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import storage
from ..functions.grid import AXES, morton3
from . import camera as cam
from . import fullframe, paging, raycast, render

MOVES = ("camera", "transfer", "clipping", "channel_matrix", "new_data")


@dataclass
class RenderSession:
    """Which kind of pass comes next, and which image is shown.

    A move starts full-frame passes; once one of them is complete and nothing moves, refinement
    begins and goes on until a pass asks for nothing.  The image shown changes only when a pass (full
    frame) or the whole refinement is complete.
    """

    mode: str = "full_frame"
    shown: int | None = None
    passes: int = 0
    matrices: dict = field(default_factory=dict)
    _complete: bool = False

    def step(self, event: str, **detail) -> str:
        """Take an event: a move, ``pass_done`` (image=, requests=) or ``idle``; return the mode of the next pass."""
        if event in MOVES:
            if event == "channel_matrix":
                self.matrices[detail["channel"]] = detail["matrix"]
            self.mode, self._complete = "full_frame", False
        elif event == "pass_done":
            self.passes += 1
            if self.mode == "full_frame":
                self.shown, self._complete = detail["image"], True
            elif self.mode == "refine" and not detail["requests"]:
                self.shown, self.mode = detail["image"], "done"
        elif event == "idle":
            if self.mode == "full_frame" and self._complete:
                self.mode = "refine"
        else:
            raise ValueError(event)
        return self.mode


class Viewer:
    """A session over a pool: passes, uploads between them, refinement at rest, and images that are published when complete.

    ``nodes`` and ``averages`` are the tree's relations, ``shade`` the transfer function.  Images are written
    as versions of one folder; a reader shows the last one with a success marker.  Changing the camera, the
    transfer function, clipping planes or a channel's matrix takes the next pass back to full frames and
    rebuilds nothing.
    """

    def __init__(self, pool, nodes, averages, shade, slots: int, path: str | None = None):
        self.pool, self.nodes, self.averages, self.shade, self.slots = pool, nodes, averages, shade, slots
        self.session, self.planes, self.resident = RenderSession(), [], None
        self.path = path or storage.new_path(pool.spark, "images")
        self._camera = None

    def look(self, camera, step: float = 1.0) -> None:
        self._camera = (camera, step)
        self.session.step("camera")

    def clip(self, planes: list) -> None:
        self.planes = planes
        self.session.step("clipping")

    def set_transfer(self, shade) -> None:
        self.shade = shade
        self.session.step("transfer")

    def set_matrix(self, channel: int, matrix) -> None:
        self.session.step("channel_matrix", channel=channel, matrix=matrix)

    def samples(self) -> DataFrame:
        """The view's samples that no plane clips: px, py, i, t, x, y, z, level, key."""
        view, step = self._camera
        rows = cam.choose_level(cam.sample_perspective(cam.perspective_rays(self.pool.spark, view, self.pool.vm), self.pool.vm, step), view, self.pool.vm)
        return storage.keep(render.clipped(rows, self.planes), "samples")

    def fetched(self, samples: DataFrame, resolved: DataFrame) -> DataFrame:
        """Intensities of a pass; a channel with a matrix is looked up where its matrix takes the sample."""
        rows = render.fetch(resolved, self.pool.bricks(), self.averages, self.pool.vm)
        for channel, matrix in self.session.matrices.items():
            vm = self.pool.vm
            moved = raycast.transform_samples(samples.select("px", "py", "i", "x", "y", "z"), {channel: matrix}).drop("c")
            inside = " and ".join(f"{a} >= 0 and {a} < {d}" for a, d in zip(AXES, vm.dims, strict=True))
            placed = moved.filter(inside).select("px", "py", "i", *(F.col(a).cast("int").alias(a) for a in AXES)).join(samples.select("px", "py", "i", "level"), ["px", "py", "i"])
            place = [F.expr(f"shiftright({a}, level) div {m}") for a, m in zip(AXES, vm.brick, strict=True)]
            there = render.resolve(placed.withColumn("key", morton3(*place, bits=vm.key_bits)), self.nodes, self.resident, "full_frame")
            own = render.fetch(there, self.pool.bricks(), self.averages, vm).filter(F.col("c") == channel)
            rows = rows.filter(F.col("c") != channel).unionByName(own)
        return rows

    def step(self) -> dict:
        """One full-frame pass with its uploads, or the whole refinement if nothing has moved since the last one."""
        samples = self.samples()
        if self.session.step("idle") == "refine":
            direct = render.resolve(samples, self.nodes, self.nodes.select("level", "key").limit(0), "direct")
            shaded = self.shade(render.waiting(self.fetched(samples, direct), direct))
            image, passes, uploads = fullframe.refine_image(shaded, self.slots, storage.keep)
            return {"mode": "refine", "passes": passes, "uploads": uploads, "image": self.publish(image, 0)}
        if self.resident is None:
            self.resident = storage.keep(self.nodes.filter((F.col("level") == self.pool.vm.top) & ~F.col("homog")).select("level", "key"), "slots")
        resolved = storage.keep(render.resolve(samples, self.nodes, self.resident), "resolved")
        asked = storage.keep(render.candidates(resolved, self.nodes, self.resident, self.pool.vm.top), "candidates")
        requests = asked.filter("waiting > 0 and resident = 0").count()
        image = self.publish(raycast.dvr_window(self.shade(self.fetched(samples, resolved))), requests)
        self.resident = storage.keep(paging.plan_uploads(asked, self.slots).select("level", "key"), "slots")
        return {"mode": "full_frame", "requests": requests, "image": image}

    def publish(self, image: DataFrame, requests: int) -> int:
        """Write a finished image as the next version and tell the controller."""
        version = 0 if self.session.shown is None else self.session.shown + 1
        image.write.mode("overwrite").parquet(f"{self.path}/version={version}")
        self.session.step("pass_done", image=version, requests=requests)
        return version

    def shown(self) -> DataFrame | None:
        """The image on the screen: the last one that was completed."""
        return None if self.session.shown is None else self.pool.spark.read.parquet(f"{self.path}/version={self.session.shown}")
