"""Lifting images to clouds with a pluggable depth teacher; one image is one packed row and nothing is shuffled."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pointloom.operators.corpora import image_colours, raster_shape
from pointloom.schema import pieces


class BlurTeacher:
    """Depth as the mean luminance of the pixel's square neighbourhood, in [0, 1]; pixels outside the image do not count."""

    def __init__(self, radius: int = 1):
        self.radius = radius

    def __call__(self, cps: np.ndarray) -> np.ndarray:
        (h, w), k, n = raster_shape(len(cps)), self.radius, len(cps)
        # sums over windows are differences of running sums, with a border of zeros
        sums = np.zeros((h + 2 * k + 1, w + 2 * k + 1), np.int64)
        rows, full = sums[k + 1 : k + 1 + h, k + 1 : k + 1 + w], np.minimum(cps, 255)
        rows[: h - 1] = full[: (h - 1) * w].reshape(h - 1, w)
        last = n - (h - 1) * w
        rows[h - 1, :last] = full[(h - 1) * w :]
        sums.cumsum(0, out=sums)
        sums.cumsum(1, out=sums)
        e = 2 * k + 1
        box = sums[e:, e:] - sums[:-e, e:] - sums[e:, :-e] + sums[:-e, :-e]
        v, u = np.arange(h), np.arange(w)
        inside = lambda at, size: np.minimum(at + k, size - 1) - np.maximum(at - k, 0) + 1
        there = inside(v, h)[:, None] * inside(u, w)
        # places of the last row behind the text
        there[max(0, h - 1 - k) :] -= np.maximum(np.minimum(u + k, w - 1) - np.maximum(u - k, last) + 1, 0)
        return box.ravel()[:n] / (there.ravel()[:n] * 255.0)


    def at(self, cps: np.ndarray, places: np.ndarray) -> np.ndarray:
        """Depths of some pixels, from their windows alone."""
        (h, w), k, n = raster_shape(len(cps)), self.radius, len(cps)
        v, u = np.divmod(places, w)
        near = np.arange(-k, k + 1)
        row, col = (v[:, None] + near)[:, :, None], (u[:, None] + near)[:, None, :]
        number = row * w + col
        inside = (row >= 0) & (row < h) & (col >= 0) & (col < w) & (number < n)
        light = np.where(inside, np.minimum(cps[np.where(inside, number, 0)], 255).astype(np.int64), 0)
        return light.sum((1, 2)) / (inside.sum((1, 2)) * 255.0)


class KernelTeacher:
    """Any user model: code points (or luminance) of one image -> depth of each pixel; loaded once a worker."""

    def __init__(self, fn: Callable[[np.ndarray], np.ndarray]):
        self.fn = fn

    def __call__(self, cps: np.ndarray) -> np.ndarray:
        return self.fn(cps)


def lift_packed(images: DataFrame, teacher=None) -> DataFrame:
    """(sample_id, cps) -> sample_id, n, x, y, z, r, g, b arrays: column -> x, depth -> y, row (up) -> z."""
    teacher = teacher or BlurTeacher(1)

    def run(batches):
        for b in (piece for whole in batches for piece in pieces(whole, pc.list_value_length(whole.column(1)))):
            out = {c: [] for c in "xyzrgb"}
            for row in b.column(1):
                cps = row.values.to_numpy(zero_copy_only=False) if row.is_valid else np.zeros(0, np.int32)
                for c, values in zip("xyzrgb", lifted(cps, teacher), strict=True):
                    out[c].append(values)
            cols = [pa.array(out[c], pa.list_(pa.float64())) for c in "xyzrgb"]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(x) for x in out["x"]], pa.int32()), *cols], ["sample_id", "n", *"xyzrgb"])

    return images.mapInArrow(run, "sample_id long, n int, " + ", ".join(f"{c} array<double>" for c in "xyzrgb"))


def depth_table(texts: DataFrame, key: str, text: str, teacher=None) -> DataFrame:
    """sample_id, n, min_depth, max_depth, sum_depth (micro-units) of every text's cloud: raster and lift in one map, of which a row a cloud
    leaves the task. A text without characters has a cloud without points."""
    teacher = teacher or BlurTeacher(1)

    def run(batches):
        for b in batches:
            rows = []
            for value in b.column(1):
                cps = np.frombuffer((value.as_py() or "").encode("utf-32-le"), np.int32)
                d = np.floor(lifted(cps, teacher)[1] * 1e6 + 0.5).astype(np.int64)
                rows.append((len(d), int(d.min()), int(d.max()), int(d.sum())) if len(d) else (0, None, None, 0))
            columns = zip(*rows, strict=True) if rows else [()] * 4
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(c, pa.int64()) for c in columns]], ["sample_id", "n", "min_depth", "max_depth", "sum_depth"])

    return texts.select(F.col(key).cast("long"), text).mapInArrow(run, "sample_id long, n long, min_depth long, max_depth long, sum_depth long")


def lifted(cps: np.ndarray, teacher, at: np.ndarray | None = None) -> tuple[np.ndarray, ...]:
    """x, y, z, r, g, b of an image's pixels, or of those numbered by ``at``; a teacher with a method ``at`` looks only at these."""
    if not len(cps):
        return (np.zeros(0),) * 6
    h, w = raster_shape(len(cps))
    if at is None:
        i, depth, own = np.arange(len(cps)), teacher(cps), cps
    else:
        i, depth, own = at, teacher.at(cps, at) if hasattr(teacher, "at") else teacher(cps)[at], cps[at]
    return ((i % w + 0.5) / w, depth, 1 - (i // w + 0.5) / h, *image_colours(own))


def unpack(clouds: DataFrame) -> DataFrame:
    """Long form of packed clouds: sample_id, point_no, x..b."""
    zipped = F.arrays_zip(*"xyzrgb")
    return clouds.select("sample_id", F.posexplode(zipped).alias("point_no", "p")).select("sample_id", F.col("point_no").cast("long").alias("point_no"), *[F.col(f"p.{c}").alias(c) for c in "xyzrgb"])


def lift_pixels(pixels: DataFrame, depth: str | DataFrame) -> DataFrame:
    """Lift exploded pixels (sample_id, u, v, w, h, r, g, b); depth is a column's name, or a frame (sample_id, u, v, depth)."""
    px = pixels.withColumn("depth", F.col(depth)) if isinstance(depth, str) else pixels.join(depth, ["sample_id", "u", "v"])
    return px.select(
        "sample_id", (F.col("v") * F.col("w") + F.col("u")).cast("long").alias("point_no"), ((F.col("u") + 0.5) / F.col("w")).alias("x"), F.col("depth").alias("y"),
        (1 - (F.col("v") + 0.5) / F.col("h")).alias("z"), "r", "g", "b",
    )


def normalise(points: DataFrame, limits: dict[str, tuple[float, float]] | None = None) -> DataFrame:
    """Coordinates to [0, 1]: by given limits (a projection), or by each cloud's own range (one window)."""
    w = Window.partitionBy("sample_id")
    out = {}
    for c in "xyz":
        lo, hi = (F.lit(float(v)) for v in limits[c]) if limits else (F.min(c).over(w), F.max(c).over(w))
        out[c] = F.when(hi > lo, (F.col(c) - lo) / (hi - lo)).otherwise(F.lit(0.0))
    return points.withColumns(out)


def drop_broken(points: DataFrame) -> DataFrame:
    """Rows with a null or NaN attribute go; count them with :func:`count_broken`."""
    ok = F.lit(True)
    for c in "xyzrgb":
        ok = ok & F.col(c).isNotNull() & ~F.isnan(c)
    return points.where(ok)


def count_broken(points: DataFrame) -> DataFrame:
    bad = F.lit(False)
    for c in "xyzrgb":
        bad = bad | F.col(c).isNull() | F.isnan(c)
    return points.agg(F.count(F.when(bad, 1)).alias("n_broken"))
