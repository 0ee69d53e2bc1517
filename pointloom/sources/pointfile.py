"""ASCII point files: one cloud a file, a line ``x y z r g b`` a point; batch and stream reads, and writes.

:func:`write_clouds` and :func:`read_clouds` use Spark's own text files, so every path that Spark reads will do (an object store as
well), tasks may be run twice, and nothing is Python. The data source ``pointfile`` reads and writes files named by their
cloud through the file system of the machine: driver and executors must share the folder.
"""

from __future__ import annotations

import glob
import os
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, DataSourceWriter, InputPartition, WriterCommitMessage

SCHEMA = "sample_id long, point_no long, x double, y double, z double, r double, g double, b double"


def write_clouds(points: DataFrame, path: str, mode: str = "error") -> None:
    """A folder a cloud with its points in order of their number; a cloud is one file."""
    line = F.concat_ws(" ", *[F.col(c).cast("string") for c in "xyzrgb"])
    ordered = points.repartition("sample_id").sortWithinPartitions("sample_id", "point_no")
    ordered.select("sample_id", line.alias("value")).write.mode(mode).partitionBy("sample_id").text(path)


def read_clouds(spark: SparkSession, path: str, stream: bool = False) -> DataFrame:
    """The points of all clouds under ``path``, numbered by their line; ``stream``: as the files arrive."""
    reader = (spark.readStream if stream else spark.read).schema("value string, sample_id long")
    lines = reader.text(path, wholetext=True).select("sample_id", F.posexplode(F.split("value", "\n")).alias("point_no", "line")).where("length(trim(line)) > 0")
    part = F.split(F.trim("line"), " +")
    return lines.select("sample_id", F.col("point_no").cast("long").alias("point_no"), *[F.get(part, F.lit(k)).cast("double").alias(c) for k, c in enumerate("xyzrgb")])


class FilePart(InputPartition):
    def __init__(self, paths):
        self.paths = paths


def _read(paths) -> Iterator[pa.RecordBatch]:
    for path in paths:
        sample = int(os.path.basename(path).split(".")[0].split("-")[0])
        with open(path) as f:
            rows = [tuple(map(float, line.split())) for line in f if line.strip()]
        cols = list(zip(*rows, strict=True)) if rows else [()] * 6
        arrays = [pa.array([sample] * len(rows), pa.int64()), pa.array(range(len(rows)), pa.int64()), *[pa.array(c, pa.float64()) for c in cols]]
        yield pa.RecordBatch.from_arrays(arrays, ["sample_id", "point_no", *"xyzrgb"])


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.path, self.size = options["path"], int(options.get("filespartition", 64))

    def partitions(self):
        files = sorted(glob.glob(f"{self.path}/*.xyz"))
        return [FilePart(files[k : k + self.size]) for k in range(0, len(files), self.size)] or [FilePart([])]

    def read(self, partition):
        return _read(partition.paths)


class _StreamReader(DataSourceStreamReader):
    """Offsets are numbers of files in name order; files must be added with growing names."""

    def __init__(self, options):
        self.path = options["path"]

    def _files(self):
        return sorted(glob.glob(f"{self.path}/*.xyz"))

    def initialOffset(self):
        return {"files": 0}

    def latestOffset(self):
        return {"files": len(self._files())}

    def partitions(self, start, end):
        return [FilePart([f]) for f in self._files()[start["files"] : end["files"]]]

    def read(self, partition):
        return _read(partition.paths)

    def commit(self, end):
        return None


class Written(WriterCommitMessage):
    def __init__(self, files):
        self.files = files


class _Writer(DataSourceWriter):
    """Each task writes its clouds under temporary names; they appear when the job commits. Co-locate samples before writing."""

    def __init__(self, options):
        self.path = options["path"]

    def write(self, rows):
        os.makedirs(self.path, exist_ok=True)
        clouds: dict[int, list] = {}
        for r in rows:
            clouds.setdefault(r["sample_id"], []).append((r["point_no"], *(r[c] for c in "xyzrgb")))
        done = []
        for sample, points in clouds.items():
            part = uuid.uuid4().hex[:12]
            tmp, final = f"{self.path}/.{sample}-{part}", f"{self.path}/{sample}-{part}.xyz"
            with open(tmp, "w") as f:
                for p in sorted(points):
                    f.write(" ".join(map(repr, p[1:])) + "\n")
            done.append((tmp, final))
        return Written(done)

    def commit(self, messages):
        for m in messages:
            for tmp, final in m.files if m else ():
                os.replace(tmp, final)

    def abort(self, messages):
        for m in messages:
            for tmp, _ in m.files if m else ():
                if os.path.exists(tmp):
                    os.remove(tmp)


class PointFileSource(DataSource):
    """``spark.dataSource.register(PointFileSource)``, then format ``pointfile``."""

    @classmethod
    def name(cls):
        return "pointfile"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return _Reader(self.options)

    def streamReader(self, schema):
        return _StreamReader(self.options)

    def writer(self, schema, overwrite):
        return _Writer(self.options)
