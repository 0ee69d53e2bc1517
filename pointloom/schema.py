"""Declared schemas and table readers."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

_local: list[str] = []

POINTS = T.StructType([T.StructField("sample_id", T.LongType()), T.StructField("point_no", T.LongType()), *(T.StructField(c, T.DoubleType()) for c in "xyzrgb")])
ATTRIBUTES = tuple("xyzrgb")
AXES = tuple("xyz")
ARMS = T.StructType([T.StructField("workload", T.StringType()), T.StructField("arm", T.StringType()), T.StructField("metric", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("stderr", T.DoubleType())])


@dataclass(frozen=True)
class GridSpec:
    """A cubic lattice with ``size`` voxels an axis, cut into patches of ``patch`` voxels an axis."""

    size: int = 224
    patch: int = 16

    @property
    def edge(self) -> float:
        return 1.0 / self.size

    @property
    def slots(self) -> int:
        return self.patch**3


G224, G32, G16 = GridSpec(224, 16), GridSpec(32, 8), GridSpec(16, 4)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Points of the clouds that a task holds at a time.
PIECE = 1 << 17


def pieces(batch: pa.RecordBatch, sizes, most: int = PIECE) -> Iterator[pa.RecordBatch]:
    """Slices of an Arrow batch whose rows' sizes sum up to ``most``, or of one larger row: Spark bounds the batches that a task gets,
    and a task must bound what it makes of them."""
    if isinstance(sizes, (pa.Array, pa.ChunkedArray)):
        sizes = sizes.fill_null(0).to_numpy(zero_copy_only=False)
    ends, lo, done = np.cumsum(sizes), 0, 0
    while lo < batch.num_rows:
        hi = max(lo + 1, int(np.searchsorted(ends, done + most, "right")))
        yield batch.slice(lo, hi - lo)
        lo, done = hi, int(ends[hi - 1])


def keep_freed() -> None:
    """Freed arrays of a worker stay with its heap and are not given back and asked for anew at every operation, which costs more than
    most operations do. Settings of glibc's allocator (largest array on the heap, free memory that stays, growth); without it, nothing."""
    try:
        for what, value in ((-3, 1 << 25), (-1, 1 << 28), (-2, 1 << 24)):
            ctypes.CDLL(None).mallopt(what, value)
    except (AttributeError, OSError):
        pass


def scratch_root(spark: SparkSession) -> str:
    """The shared folder the cluster names; a local one only where none is set (tests, local mode)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root
    if not _local:
        _local.append("file://" + tempfile.mkdtemp(prefix="pointloom-"))
    return _local[0]


def scratch_path(spark: SparkSession) -> str:
    """A new path in the shared folder; what is written there goes when the driver's JVM ends."""
    folder = f"{scratch_root(spark)}/pointloom-{uuid.uuid4().hex}"
    hfolder = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = hfolder.getFileSystem(spark._jsc.hadoopConfiguration())
    # only what exists can be marked to go
    fs.mkdirs(hfolder)
    fs.deleteOnExit(hfolder)
    return f"{folder}/t"


def scratch_table(df: DataFrame, *by: str) -> DataFrame:
    """``df`` written once to the shared folder, partitioned by columns if named, and read back."""
    path = scratch_path(df.sparkSession)
    df.write.partitionBy(*by).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def validate(df: DataFrame, schema: T.StructType = POINTS) -> DataFrame:
    """``df`` restricted to the schema's columns; a clear error names what is missing."""
    missing = [f.name for f in schema if f.name not in df.columns]
    if missing:
        raise ValueError(f"columns {missing} are missing; got {df.columns}")
    return df.select(*[df[f.name].cast(f.dataType).alias(f.name) for f in schema])
