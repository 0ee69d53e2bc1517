"""Growing clouds: points arrive as a stream, voxels and tokens are kept up to date."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from pointloom.operators.corpora import event_clouds
from pointloom.schema import G16, GridSpec


def event_stream(spark: SparkSession, path: str, watermark: str = "1 hour") -> DataFrame:
    """File stream of an events folder: event time as a timestamp, a watermark, and replayed events dropped."""
    schema = spark.read.parquet(path).schema
    raw = spark.readStream.schema(schema).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def event_points(events: DataFrame) -> DataFrame:
    t = F.col("ts")
    second = F.hour(t) * 3600 + F.minute(t) * 60 + F.second(t)
    return events.select(
        F.col("user_id").cast("long").alias("sample_id"), F.col("event_id").cast("long").alias("point_no"), (second / 86400).alias("x"), (F.least(F.col("value"), F.lit(600.0)) / 600).alias("y"),
        (F.get_json_object("props", "$.k").cast("long") / 100).alias("z"), F.when(F.col("event_type") == "click", 1.0).otherwise(0.0).alias("r"), F.lit(0.0).alias("g"), F.lit(0.0).alias("b"),
    )


class VoxelState(StatefulProcessor):
    """The best point of every voxel of one sample; emits the sample's number of voxels and patches after each batch.

    A representative is a maximum, so it can be merged in any order: the state after all batches is that of one batch. The
    counts are kept as state and a batch is first reduced to its voxels, so the work is that of the new voxels.
    """

    def __init__(self, grid: GridSpec):
        self.grid = grid

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.voxels = handle.getMapState("voxels", "voxel long", "score long, point_no long")
        self.patches = handle.getMapState("patches", "patch long", "n_voxels long")
        self.counts = handle.getValueState("counts", "n_points long, n_voxels long, n_patches long")

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        n, n_voxels, n_patches = self.counts.get() if self.counts.exists() else (0, 0, 0)
        a = self.grid.patch
        for pdf in rows:
            n += len(pdf)
            k = np.clip(np.floor(pdf[list("xyz")].to_numpy() / self.grid.edge), 0, self.grid.size - 1).astype(np.int64)
            flat = (k[:, 0] * 1024 + k[:, 1]) * 1024 + k[:, 2]
            score, no = np.floor(pdf[list("xyzrgb")].to_numpy().sum(1) * 1e6 + 0.5).astype(np.int64), pdf["point_no"].to_numpy()
            # the batch's best point of each voxel
            order = np.lexsort((-no, -score, flat))
            best = order[np.concatenate(([True], np.diff(flat[order]) != 0))] if len(order) else order
            for v, s, p in zip(flat[best].tolist(), score[best].tolist(), no[best].tolist(), strict=True):
                old = self.voxels.getValue((v,)) if self.voxels.containsKey((v,)) else None
                if old is None:
                    n_voxels += 1
                    cell = ((v >> 20) // a * 1024 + ((v >> 10) & 1023) // a) * 1024 + (v & 1023) // a
                    held = self.patches.getValue((cell,))[0] if self.patches.containsKey((cell,)) else 0
                    n_patches += held == 0
                    self.patches.updateValue((cell,), (held + 1,))
                if old is None or (s, p) > (old[0], old[1]):
                    self.voxels.updateValue((v,), (s, p))
        self.counts.update((n, n_voxels, n_patches))
        yield pd.DataFrame({"sample_id": [key[0]], "n_points": [n], "n_voxels": [n_voxels], "n_patches": [n_patches]})

    def close(self) -> None:
        pass


STATS = "sample_id long, n_points long, n_voxels long, n_patches long"


def stateful_tokens(points: DataFrame, grid: GridSpec = G16) -> DataFrame:
    """Per sample running statistics in update mode; needs the RocksDB state store."""
    return points.groupBy("sample_id").transformWithStateInPandas(VoxelState(grid), STATS, "Update", "None")


def voxel_counts(points: DataFrame, grid: GridSpec = G16) -> DataFrame:
    """The stateful operator's twin with built-in state: points a voxel, in update or complete mode."""
    from pointloom.operators import voxel

    return voxel.assign(points, grid).groupBy("sample_id", *voxel.KEY).agg(F.count("*").alias("n_points"))


def run_to_table(spark: SparkSession, stream: DataFrame, path: str, keys: list[str], count: str) -> DataFrame:
    """Everything available now, in update mode, into Parquet under ``path``: each batch appends the rows that it changed under its
    number (a batch that is run again replaces its own), and the latest row of a key counts, which is the one of the largest ``count``."""

    def append(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/out/batch={batch}")

    q = stream.writeStream.foreachBatch(append).outputMode("update").trigger(availableNow=True).option("checkpointLocation", f"{path}/checkpoint").start()
    q.awaitTermination()
    # a file name with a star before it is found even where no batch was written
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in stream.schema)
    if q.lastProgress is None:
        return spark.createDataFrame([], schema)
    return spark.read.schema(schema).parquet(f"{path}/out").groupBy(*keys).agg(F.max(count).alias(count))


def batch_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    return event_clouds(spark, sf_dir).select("sample_id", "point_no", *"xyzrgb")
