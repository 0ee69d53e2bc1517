"""Raw image files as packed rows: binary PPM (P6) bytes through Spark's binaryFile source, decoded in Arrow batches."""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

SCHEMA = "sample_id long, path string, h int, w int, rgb binary"
_HEAD = re.compile(rb"P6(?:\s+#[^\n]*)*\s+(\d+)(?:\s+#[^\n]*)*\s+(\d+)(?:\s+#[^\n]*)*\s+(\d+)\s")


def decode_ppm(data: bytes) -> tuple[int, int, bytes]:
    """(height, width, interleaved 8-bit colours); a file that is no 8-bit P6 image raises."""
    m = _HEAD.match(data)
    if not m or int(m[3]) > 255:
        raise ValueError("not an 8-bit binary PPM file")
    w, h = int(m[1]), int(m[2])
    body = data[m.end() : m.end() + 3 * w * h]
    if len(body) != 3 * w * h:
        raise ValueError("the image is cut short")
    return h, w, body


def encode_ppm(rgb: np.ndarray) -> bytes:
    h, w, _ = rgb.shape
    return b"P6\n%d %d\n255\n" % (w, h) + rgb.astype(np.uint8).tobytes()


def read_ppm(spark: SparkSession, path: str) -> DataFrame:
    """One row an image; the sample's number is the leading number of the file's name."""

    def run(batches):
        for b in batches:
            names = [p.rsplit("/", 1)[-1] for p in b.column(0).to_pylist()]
            ids = [int(re.match(r"\d+", n)[0]) if re.match(r"\d+", n) else None for n in names]
            out = [decode_ppm(d) for d in b.column(1).to_pylist()]
            h, w, rgb = zip(*out, strict=True) if out else ((), (), ())
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), b.column(0), pa.array(h, pa.int32()), pa.array(w, pa.int32()), pa.array(rgb, pa.binary())], ["sample_id", "path", "h", "w", "rgb"])

    return spark.read.format("binaryFile").load(path).select("path", "content").mapInArrow(run, SCHEMA)


def lift_images(images: DataFrame, teacher=None) -> DataFrame:
    """(sample_id, h, w, rgb) -> packed clouds, one point a pixel; ``teacher`` gets luminance (h, w) in [0, 1] and gives depth."""
    teacher = teacher or mean_of_neighbours

    def run(batches):
        for b in batches:
            out = {c: [] for c in "xyzrgb"}
            for h, w, rgb in zip(*(b.column(k).to_pylist() for k in (1, 2, 3)), strict=True):
                colour = np.frombuffer(rgb, np.uint8).reshape(h, w, 3) / 255
                depth = teacher(colour @ np.array([0.299, 0.587, 0.114]))
                v, u = np.divmod(np.arange(h * w), w)
                for c, x in zip("xyzrgb", ((u + 0.5) / w, depth.ravel(), 1 - (v + 0.5) / h, *colour.reshape(-1, 3).T), strict=True):
                    out[c].append(np.ascontiguousarray(x))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(x) for x in out["x"]], pa.int32()), *[pa.array(out[c], pa.list_(pa.float64())) for c in "xyzrgb"]], ["sample_id", "n", *"xyzrgb"])

    return images.select("sample_id", "h", "w", "rgb").mapInArrow(run, "sample_id long, n int, " + ", ".join(f"{c} array<double>" for c in "xyzrgb"))


def mean_of_neighbours(lum: np.ndarray) -> np.ndarray:
    """Stand-in teacher: the mean luminance of each pixel's 3 x 3 neighbourhood."""
    n = np.pad(np.ones_like(lum), 1)
    s = np.pad(lum, 1)
    box = lambda a: sum(a[i : i + lum.shape[0], j : j + lum.shape[1]] for i in range(3) for j in range(3))
    return box(s) / box(n)
